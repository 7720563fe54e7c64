"""Queries for the methods: curves, leaf summaries, roll-ups, grids, extensions, baselines, measures."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracles as O
from ..functions import levels as L
from ..functions import readout as R
from ..functions.curve import PROBIT, SLACK, FlushRules
from ..operators import baselines as B
from ..operators import extensions as X
from ..operators import measures as A
from ..operators import relational as rel
from ..operators.digest import Scheme
from ..operators.leaf import digest_agg, most_held, summarize
from ..operators.rollup import merge, merge_levels
from ..registry import query
from ..sources.tables import ORDER, hierarchy, table

FIVE, R11 = list(L.FIVE), list(L.REPORT_11)
LEVELS = [0.25, 0.5, 0.9]
EXACT = Scheme(grid="report11", report="report11", batch=None)  # a leaf as one batch
EXACT5 = Scheme(grid="five", report="five", batch=None)


def ev(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events")


def li(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem")


def flat(df: DataFrame, keys: list[str], names: list[str] | None = None) -> DataFrame:
    out = R.long(df, keys, digits=7)
    for a, b in zip(keys, names or keys, strict=True):
        out = out.withColumnRenamed(a, b)
    return out


# ---- SQL pieces -------------------------------------------------------------------------------------------
EV_RAW = "SELECT user_id AS k, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn, value AS x FROM events"
LI_ORDER = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice"
LI_RAW = f"SELECT l_suppkey AS k, row_number() OVER (PARTITION BY l_suppkey ORDER BY {LI_ORDER}) AS rn, l_extendedprice AS x FROM lineitem"


def leaf_lists(src: str, levels: list[float], raw_below: int = 0) -> str:
    """CTEs ``ll(k, n, a)``, ``dg(k, n, m, p, v)``: groups of ``(k, x)`` as one batch; smaller ones are raw in ``rw(k, n, x)``."""
    return f"""ll AS MATERIALIZED (SELECT k, count(*) AS n, list_sort(list(x)) AS a FROM ({src}) AS s GROUP BY k),
dg AS MATERIALIZED (SELECT k, CAST(n AS DOUBLE) AS n, m, p, CASE WHEN p <= 0 THEN a[1] WHEN p >= 1 THEN a[n] ELSE (a[greatest(1, CAST(ceil(p * n - 1e-12 * n) AS BIGINT))] + a[least(n, CAST(floor(p * n + 1e-12 * n) AS BIGINT) + 1)]) / 2 END AS v
  FROM ll CROSS JOIN ({O.levels_sql(levels)}) AS lv WHERE n >= {raw_below}),
rw AS MATERIALIZED (SELECT k, n, unnest(a) AS x FROM ll WHERE n < {raw_below})"""


def rolled(src: str, levels: list[float], parent: str, order: str, flushes: int, batch: int, select: str, raw_below: int = 0, knots: list[float] | None = None, **kw) -> str:
    """Roll-up of one-batch leaves: ``parent`` and ``order`` are SQL over the leaf key k."""
    pre = leaf_lists(src, levels, raw_below)
    pre += f""",
od AS MATERIALIZED (SELECT k AS leaf, {parent} AS k, row_number() OVER (PARTITION BY {parent} ORDER BY {order}) AS rn FROM ll)"""
    dig = "SELECT od.k, od.rn, od.rn AS cid, dg.n, dg.m, dg.p, dg.v FROM od JOIN dg ON dg.k = od.leaf"
    raw = "SELECT od.k, od.rn, rw.x FROM od JOIN rw ON rw.k = od.leaf" if raw_below else None
    body = O.unrolled(knots or levels, flushes, batch, raw, dig, **kw)
    return f"WITH {pre},\n{body}\nSELECT {select} FROM kn_{flushes}"


VALUE = "p AS level, round(v, 7) AS value"

# ---- curves and the flush ---------------------------------------------------------------------------------


@query("""SELECT user_id, p AS level, round(greatest(least(p, 1 - 0.5 / n), 0.5 / n), 9) AS trimmed
FROM (SELECT user_id, count(*) AS n FROM events GROUP BY user_id) AS c CROSS JOIN (%s) AS lv""" % O.levels_sql(R11))
def trim_levels(spark, sf):
    """Levels clipped by half an observation, per user."""
    n = ev(spark, sf).groupBy("user_id").agg(F.count("*").alias("n"))
    d = n.select("user_id", F.struct("n", F.lit("report11").alias("grid")).alias("digest"))
    return d.select("user_id", F.explode(F.arrays_zip(R.levels("digest").alias("p"), R.trimmed("digest").alias("q"))).alias("c")).select("user_id", F.col("c.p").alias("level"), F.round("c.q", 9).alias("trimmed"))


def _user_digests(spark, sf, scheme=EXACT, keys=("user_id",)):
    return summarize(ev(spark, sf), list(keys), "value", ORDER["events"], scheme)


_AT = [5.0, 20.0, 60.0, 150.0, 1e6, -1.0]


def _cdf_sql(interp: str) -> str:
    g = (lambda q: f"ln({q} / (1 - {q}))") if interp == "logit" else (lambda q: q)
    mid = f"({g('a.q')} + ({g('b.q')} - {g('a.q')}) * (t.x - a.v) / (b.v - a.v))"
    mid = f"1 / (1 + exp(-{mid}))" if interp == "logit" else mid
    return f"""WITH {leaf_lists("SELECT user_id AS k, value AS x FROM events", R11)},
q AS (SELECT k, m, v, greatest(least(p, 1 - 0.5 / n), 0.5 / n) AS q FROM dg),
t AS (SELECT ll.k, xs.x, max(q.m) FILTER (WHERE q.v <= xs.x) AS m FROM ll CROSS JOIN (SELECT unnest({_AT}) AS x) AS xs JOIN q ON q.k = ll.k GROUP BY ll.k, xs.x)
SELECT t.k AS user_id, CAST(t.x AS DOUBLE) AS x, round(CASE WHEN t.m IS NULL THEN 0 WHEN t.m = {len(R11) - 1} THEN 1 ELSE {mid} END, 9) AS share
FROM t LEFT JOIN q AS a ON a.k = t.k AND a.m = t.m LEFT JOIN q AS b ON b.k = t.k AND b.m = t.m + 1"""


def _cdf(interp: str) -> Callable:
    def run(spark, sf):
        d = _user_digests(spark, sf).select("user_id", "digest", F.explode(F.array(*[F.lit(x) for x in _AT])).alias("x"))
        return d.select("user_id", "x", F.round(R.cdf_at("digest", F.col("x"), interp=interp), 9).alias("share"))

    return run


query(_cdf_sql("linear"), "knot_cdf_linear")(_cdf("linear"))
query(_cdf_sql("logit"), "knot_cdf_logit")(_cdf("logit"))


@query()
def interp_custom(spark, sf):
    """A leaf with another transform of the probability (probit)."""
    return flat(summarize(ev(spark, sf), ["event_type"], "value", ORDER["events"], Scheme(batch=100, interp=PROBIT)), ["event_type"])


@query("""SELECT event_type, x, CAST(hi - c AS DOUBLE) AS lo, CAST(hi AS DOUBLE) AS hi, CAST(total AS DOUBLE) AS total FROM (
SELECT event_type, value AS x, count(*) AS c, sum(count(*)) OVER (PARTITION BY event_type ORDER BY value) AS hi, sum(count(*)) OVER (PARTITION BY event_type) AS total FROM events GROUP BY event_type, value) AS s""")
def step_cdf(spark, sf):
    return rel.step_cdf(ev(spark, sf), ["event_type"], "value")


_SUP = "SELECT l_suppkey AS k, l_extendedprice AS x FROM lineitem"
_SUP_NATION = "(SELECT s_nationkey FROM supplier WHERE s_suppkey = ll.k)"


def _supplier_digests(spark, sf, scheme=EXACT5):
    d = summarize(li(spark, sf), ["l_suppkey"], "l_extendedprice", ORDER["lineitem"], scheme)
    s = table(spark, sf, "supplier")
    return d.join(s, d.l_suppkey == s.s_suppkey).select("s_nationkey", "l_suppkey", "digest")


def _limits_sql(limits: str) -> str:
    body = rolled(_SUP, FIVE, _SUP_NATION, "k", 1, 10**9, "0", limits=limits)
    return body[: body.rindex("\nSELECT")] + "\nSELECT k AS s_nationkey, round(x, 7) AS x, round(lo, 7) AS lo, round(hi, 7) AS hi FROM li_1"


def _sweep(limits: str) -> Callable:
    def run(spark, sf):
        seg = rel.segments(_supplier_digests(spark, sf), ["s_nationkey"])
        return rel.sweep(seg, ["s_nationkey"], FlushRules(limits=limits)).select("s_nationkey", *[F.round(c, 7).alias(c) for c in ("x", "lo", "hi")])

    return run


query(_limits_sql("as_stated"), "blend_sweep")(_sweep("as_stated"))
query(_limits_sql("two_sided"), "blend_two")(_sweep("two_sided"))


def _one_blend(keys_sql: str) -> str:
    return rolled(_SUP, FIVE, _SUP_NATION, "k", 1, 10**9, f"{keys_sql}, {VALUE}")


@query(_one_blend("k AS s_nationkey"))
def invert_linear(spark, sf):
    """Relational blend and inversion of all supplier digests of a nation."""
    out = rel.merge_one_blend(_supplier_digests(spark, sf), ["s_nationkey"], FIVE)
    return out.select("s_nationkey", "level", F.round("value", 7).alias("value"))


query(_one_blend("k AS s_nationkey"), "merge_one_blend")(
    lambda spark, sf: flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", ["l_suppkey"], EXACT5), ["s_nationkey"])
)


@query(rolled(_SUP, FIVE, _SUP_NATION, "k", 1, 10**9, f"k AS s_nationkey, {VALUE}", interp="logit"))
def invert_logit(spark, sf):
    return flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", ["l_suppkey"], EXACT5.but(interp="logit")), ["s_nationkey"])


def _leaf_sql(raw: str, key: str, levels: list[float], flushes: int, batch: int, value: str = VALUE, **kw) -> str:
    return O.final(O.unrolled(levels, flushes, batch, raw, **kw), flushes, f"k AS {key}, {value}")


@query(_leaf_sql(EV_RAW, "user_id", FIVE, 1, 200))
def flush_once(spark, sf):
    return flat(_user_digests(spark, sf, Scheme(grid="five", report="five", batch=200)), ["user_id"])


@query(_leaf_sql(EV_RAW, "user_id", FIVE, 4, 30))
def flush_partial(spark, sf):
    """Users end with a shorter batch."""
    return flat(_user_digests(spark, sf, Scheme(grid="five", report="five", batch=30)), ["user_id"])


def _rules(name: str, rules: FlushRules, batch: int = 40) -> None:
    sql = _leaf_sql(EV_RAW, "user_id", FIVE, 3, batch, plateau=rules.plateau, limits=rules.limits, bracket=rules.bracket)
    query(sql, name)(lambda spark, sf: flat(_user_digests(spark, sf, Scheme(grid="five", report="five", batch=batch, rules=rules)), ["user_id"]))


_rules("rules_low", FlushRules("low"))
_rules("rules_high", FlushRules("high"))
_rules("rules_two_sided", FlushRules(limits="two_sided"))
_rules("rules_exact_inverse", FlushRules("mid", "two_sided", "inner"))


@query("SELECT user_id, count(*) AS n, min(value) AS low, max(value) AS high FROM events GROUP BY user_id")
def extremes(spark, sf):
    """The outer values of a digest are the exact minimum and maximum, after several flushes."""
    d = _user_digests(spark, sf, Scheme(batch=20))
    return d.select("user_id", F.col("digest.n").alias("n"), F.get("digest.vals", F.lit(0)).alias("low"), F.element_at("digest.vals", -1).alias("high"))


# ---- leaf -------------------------------------------------------------------------------------------------
_S41 = Scheme(grid="report11", report="report11", batch=41)
_S100 = Scheme(grid="report11", report="report11", batch=100)
query(_leaf_sql(EV_RAW, "user_id", R11, 3, 41), "leaf_by_user")(lambda spark, sf: flat(_user_digests(spark, sf, _S41), ["user_id"]))
query(_leaf_sql(LI_RAW, "l_suppkey", R11, 8, 100), "leaf_by_supplier")(
    lambda spark, sf: flat(summarize(li(spark, sf), ["l_suppkey"], "l_extendedprice", ORDER["lineitem"], _S100), ["l_suppkey"])
)
query(_leaf_sql(EV_RAW, "user_id", R11, 3, 41), "leaf_group_engine")(
    lambda spark, sf: flat(summarize(ev(spark, sf), ["user_id"], "value", ORDER["events"], _S41, engine="group"), ["user_id"])
)


@query("SELECT l_suppkey, count(*) AS n, min(l_extendedprice) AS low, max(l_extendedprice) AS high FROM lineitem GROUP BY l_suppkey")
def leaf_partial(spark, sf):
    """Map-side summaries, then a roll-up: counts and extremes are exact whatever the layout."""
    d = summarize(li(spark, sf), ["l_suppkey"], "l_extendedprice", (), _S100, engine="partial")
    return d.select("l_suppkey", F.col("digest.n").alias("n"), F.get("digest.vals", F.lit(0)).alias("low"), F.element_at("digest.vals", -1).alias("high"))


_MID = f"""WITH {leaf_lists('SELECT user_id AS k, value AS x FROM events', R11)} SELECT k AS user_id, p AS level, round(v, 7) AS value FROM dg"""


@query(_MID)
def leaf_one_flush(spark, sf):
    """Windows only: a group as one batch."""
    return rel.one_flush(ev(spark, sf), ["user_id"], "value", R11).withColumn("value", F.round("value", 7))


query("""SELECT user_id, date_trunc('hour', ts) AS hour, count(*) AS n, list_sort(list(value)) AS vals FROM events GROUP BY ALL HAVING count(*) < 11""", "raw_digests")(
    lambda spark, sf: summarize(ev(spark, sf).withColumn("hour", F.date_trunc("hour", "ts").cast("timestamp_ntz")), ["user_id", "hour"], "value", ORDER["events"])
    .where("digest.raw")
    .select("user_id", "hour", F.col("digest.n").alias("n"), F.col("digest.vals").alias("vals"))
)

query(O.final(O.unrolled([float(x) for x in np.union1d(L.uniform_levels(21), L.FIVE)], 3, 41, EV_RAW), 3, f"k AS user_id, {VALUE}", f"WHERE p IN ({', '.join(map(repr, map(float, FIVE)))})"), "report_subset")(
    lambda spark, sf: flat(_user_digests(spark, sf, Scheme(grid="uniform:21", report="five", batch=41, report_mode="subset")), ["user_id"])
)


@query(f"""WITH {leaf_lists('SELECT user_id AS k, value AS x FROM events', R11)},
q AS (SELECT k, m, v, greatest(least(p, 1 - 0.5 / n), 0.5 / n) AS q FROM dg),
t AS (SELECT ll.k, ps.p, max(q.m) FILTER (WHERE q.q <= ps.p) AS m FROM ll CROSS JOIN (SELECT unnest([0.001, 0.3, 0.62, 0.97]) AS p) AS ps JOIN q ON q.k = ll.k GROUP BY ll.k, ps.p)
SELECT t.k AS user_id, CAST(t.p AS DOUBLE) AS level, round(CASE WHEN t.m IS NULL THEN z.v WHEN t.m = 10 THEN a.v WHEN b.q > a.q THEN a.v + (b.v - a.v) * (t.p - a.q) / (b.q - a.q) ELSE a.v END, 7) AS value
FROM t LEFT JOIN q AS a ON a.k = t.k AND a.m = t.m LEFT JOIN q AS b ON b.k = t.k AND b.m = t.m + 1 JOIN q AS z ON z.k = t.k AND z.m = 0""")
def quantile_at(spark, sf):
    """Digests read at levels that they do not store."""
    d = _user_digests(spark, sf).select("user_id", "digest", F.explode(F.array(*[F.lit(p) for p in (0.001, 0.3, 0.62, 0.97)])).alias("level"))
    return d.select("user_id", "level", F.round(R.quantile_at("digest", F.col("level")), 7).alias("value"))


query(_cdf_sql("linear"), "cdf_at")(_cdf("linear"))
query(_cdf_sql("linear").replace("AS share", "AS below").replace("SELECT t.k AS user_id", "SELECT user_id, x, round(1 - below, 9) AS above FROM (SELECT t.k AS user_id", 1) + ") AS z", "share_above")(
    lambda spark, sf: _cdf("linear")(spark, sf).select("user_id", "x", F.round(1 - F.col("share"), 9).alias("above"))
)

_METRICS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
query(
    O.final(
        O.unrolled(FIVE, 3, 250, " UNION ALL ".join(f"SELECT struct_pack(s := l_suppkey, metric := '{m}') AS k, row_number() OVER (PARTITION BY l_suppkey ORDER BY {LI_ORDER}) AS rn, {m} AS x FROM lineitem" for m in _METRICS)),
        3, f"k.s AS l_suppkey, k.metric AS metric, {VALUE}",
    ),
    "leaf_multi_metric",
)(lambda spark, sf: flat(summarize(li(spark, sf).withColumn("_p", F.col("l_extendedprice")), ["l_suppkey"], "", ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "_p"], Scheme(grid="five", report="five", batch=250), metrics=_METRICS), ["l_suppkey", "metric"]))


@query(_MID, "digest_agg")
def _digest_agg(spark, sf):
    return flat(ev(spark, sf).groupBy("user_id").agg(digest_agg(EXACT)("value").alias("digest")), ["user_id"])


@query(_leaf_sql(EV_RAW, "user_id", R11, 5, 20))
def leaf_resume(spark, sf):
    """The first 40 values of every user, stored at a flush boundary, then the rest."""
    from pyspark.sql import Window

    s = _S41.but(batch=20)
    e = ev(spark, sf).withColumn("rn", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    head = summarize(e.where("rn <= 40"), ["user_id"], "value", ["rn"], s, emit_state=True)
    return flat(summarize(e.where("rn > 40"), ["user_id"], "value", ["rn"], s, initial=head), ["user_id"])


_LOG_RAW = "SELECT source AS k, row_number() OVER (PARTITION BY source ORDER BY doc_id) AS rn, ln(n_chars) AS x FROM documents"
query(_leaf_sql(_LOG_RAW, "source", FIVE, 3, 20, "p AS level, round(exp(v), 7) AS value"), "leaf_log")(
    lambda spark, sf: flat(summarize(table(spark, sf, "documents"), ["source"], "n_chars", ["doc_id"], Scheme(grid="five", report="five", batch=20, scale="log")), ["source"])
)
_SLOG_RAW = "SELECT c_nationkey AS k, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS rn, sign(c_acctbal) * ln(1 + abs(c_acctbal)) AS x FROM customer"
query(_leaf_sql(_SLOG_RAW, "c_nationkey", FIVE, 4, 25, "p AS level, round(sign(v) * (exp(abs(v)) - 1), 7) AS value"), "leaf_slog")(
    lambda spark, sf: flat(summarize(table(spark, sf, "customer"), ["c_nationkey"], "c_acctbal", ["c_custkey"], Scheme(grid="five", report="five", batch=25, scale="slog")), ["c_nationkey"])
)
query(_leaf_sql(EV_RAW, "user_id", [float(p) for p in L.grid("report10").levels], 3, 41, interp="logit"), "leaf_logit")(
    lambda spark, sf: flat(_user_digests(spark, sf, Scheme(grid="report10", report="report10", batch=41, interp="logit")), ["user_id"])
)

# ---- roll-up ----------------------------------------------------------------------------------------------
query(rolled(_SUP, FIVE, _SUP_NATION, "k", 6, 3, f"k AS s_nationkey, {VALUE}"), "merge_suppliers")(
    lambda spark, sf: flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", ["l_suppkey"], EXACT5.but(batch=3)), ["s_nationkey"])
)
_UT = "SELECT struct_pack(u := user_id, t := event_type) AS k, value AS x FROM events"
query(rolled(_UT, R11, "k.t", "k.u", 3, 60, f"k AS event_type, {VALUE}", raw_below=11), "merge_mixed")(
    lambda spark, sf: flat(merge(_user_digests(spark, sf, EXACT, ("user_id", "event_type")), ["event_type"], "digest", ["user_id"], EXACT.but(batch=60)), ["event_type"])
)
query(
    f"""WITH {leaf_lists("SELECT date_trunc('day', ts) AS k, value AS x FROM events", R11)} SELECT k AS day, p AS level, round(v, 7) AS value FROM dg""", "merge_raw_only"
)(lambda spark, sf: flat(merge(_user_hours(spark, sf), [F.date_trunc("day", "hour").cast("timestamp_ntz").alias("day")], "digest", ["hour", "user_id"], EXACT), ["day"]))


def _user_hours(spark, sf, scheme=EXACT):
    e = ev(spark, sf).withColumn("hour", F.date_trunc("hour", "ts").cast("timestamp_ntz"))
    return summarize(e, ["user_id", "hour"], "value", ORDER["events"], scheme)


def _facts(df: DataFrame, *keys: str) -> DataFrame:
    return df.select(*keys, F.col("digest.n").alias("n"), F.col("digest.parts").alias("parts"), F.array_min("digest.vals").alias("low"), F.array_max("digest.vals").alias("high"))


query("SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS parts, min(value) AS low, max(value) AS high FROM events GROUP BY event_type", "merge_counts")(
    lambda spark, sf: _facts(merge(_user_digests(spark, sf, EXACT, ("user_id", "event_type")), ["event_type"], "digest", ["user_id"], _S41), "event_type")
)
_HIER = "events AS e JOIN customer AS c ON c.c_custkey = e.user_id JOIN nation AS n ON n.n_nationkey = c.c_nationkey JOIN region AS r ON r.r_regionkey = n.n_regionkey"


def tier_sql(below: str, parent: str, order: str, flushes: int, batch: int, select: str) -> str:
    """One more roll-up in SQL: ``below`` gives ``(leaf, n, m, p, v)``, ``parent`` and ``order`` are SQL over leaf."""
    dig = f"SELECT {parent} AS k, dense_rank() OVER (PARTITION BY {parent} ORDER BY {order}) AS rn, dense_rank() OVER (PARTITION BY {parent} ORDER BY {order}) AS cid, n, m, p, v FROM ({below}) AS below"
    return f"WITH {O.unrolled(FIVE, flushes, batch, None, dig)}\nSELECT {select} FROM kn_{flushes}"


_NATIONS = rolled("SELECT user_id AS k, value AS x FROM events", FIVE, "(SELECT n_name FROM customer JOIN nation ON n_nationkey = c_nationkey WHERE c_custkey = ll.k)", "k", 16, 5, "k AS leaf, w AS n, m, p, v")


@query(tier_sql(_NATIONS, "(SELECT r_name FROM nation JOIN region ON r_regionkey = n_regionkey WHERE n_name = leaf)", "leaf", 3, 2, f"k AS region, CAST(w AS BIGINT) AS n, {VALUE}"))
def hier_user_nation_region(spark, sf):
    """User -> nation -> region; every tier reads the digests of the one below."""
    d = _user_digests(spark, sf, EXACT5).join(hierarchy(spark, sf), "user_id").select("region", "nation", "user_id", "digest")
    nations = merge(d, ["region", "nation"], "digest", ["user_id"], EXACT5.but(batch=5))
    regions = merge(nations, ["region"], "digest", ["nation"], EXACT5.but(batch=2))
    return R.long(regions.withColumn("n", F.col("digest.n")), ["region", "n"], digits=7)


query(
    rolled("SELECT user_id AS k, value AS x FROM events", FIVE, "(SELECT n_name FROM customer JOIN nation ON n_nationkey = c_nationkey WHERE c_custkey = ll.k)", "k", 4, 5, f"k AS nation, {VALUE}"),
    "hier_nation_tier",
)(lambda spark, sf: flat(merge(_user_digests(spark, sf, EXACT5).join(hierarchy(spark, sf), "user_id"), ["nation"], "digest", ["user_id"], EXACT5.but(batch=5)), ["nation"]))


_DAYS_OF_HOURS = rolled("SELECT date_trunc('hour', ts) AS k, value AS x FROM events", FIVE, "date_trunc('day', k)", "k", 1, 24, "k AS leaf, w AS n, m, p, v", raw_below=5)


@query(tier_sql(_DAYS_OF_HOURS, "date_trunc('month', leaf)", "leaf", 4, 10, f"k AS month, CAST(w AS BIGINT) AS n, {VALUE}"))
def hier_hour_day_month(spark, sf):
    e = ev(spark, sf).withColumn("hour", F.date_trunc("hour", "ts").cast("timestamp_ntz"))
    hours = summarize(e, ["hour"], "value", ORDER["events"], EXACT5)
    day, month = F.date_trunc("day", "hour").cast("timestamp_ntz").alias("day"), F.date_trunc("month", "day").cast("timestamp_ntz").alias("month")
    days = merge(hours, [day], "digest", ["hour"], EXACT5.but(batch=24))
    return R.long(merge(days, [month], "digest", ["day"], EXACT5.but(batch=10)).withColumn("n", F.col("digest.n")), ["month", "n"], digits=7)


@query("SELECT path, CAST(n AS BIGINT) AS n FROM (SELECT count(*) AS n FROM events) AS z CROSS JOIN (VALUES ('by_hour_then_users'), ('by_user_then_hours')) AS p(path)")
def path_compare(spark, sf):
    """Users first or hours first: counts agree exactly (values within roll-up accuracy, see tests)."""
    cells = _user_hours(spark, sf, _S41)
    a = merge(merge(cells, ["user_id"], "digest", ["hour"], _S41), [], "digest", ["user_id"], _S41)
    b = merge(merge(cells, ["hour"], "digest", ["user_id"], _S41), [], "digest", ["hour"], _S41)
    pick = lambda d, p: d.select(F.lit(p).alias("path"), F.col("digest.n").alias("n"))
    return pick(a, "by_user_then_hours").unionAll(pick(b, "by_hour_then_users"))


_RS = "SELECT struct_pack(u := user_id, s := c_mktsegment, r := r_name) AS k, value AS x FROM " + _HIER


def slice_quantiles(store: DataFrame, leaves: DataFrame | None, where: str, keys: list[str], levels: list[float], on: tuple[str, ...] = ("user_id",)) -> DataFrame:
    """Digests of a store restricted by a filter and to a set of leaves, whose attributes may be keys, blended at once per key."""
    picked = store.where(where)
    if leaves is not None:
        picked = picked.join(leaves, list(on))
    return rel.merge_one_blend(picked, keys, levels)


query(rolled(_RS + " WHERE r_name IN ('ASIA', 'EUROPE')", FIVE, "k.r", "k.u", 1, 10**9, f"k AS region, {VALUE}"), "slice_region")(
    lambda spark, sf: slice_quantiles(_user_digests(spark, sf, EXACT5), hierarchy(spark, sf).where("region in ('ASIA', 'EUROPE')"), "user_id is not null", ["region"], FIVE)
    .select("region", "level", F.round("value", 7).alias("value"))
)
_WEEK = "SELECT struct_pack(u := user_id, s := c_mktsegment, d := date_trunc('day', ts)) AS k, value AS x FROM " + _HIER + " WHERE ts >= TIMESTAMP '2024-01-08' AND ts < TIMESTAMP '2024-01-15'"


@query(rolled(_WEEK, FIVE, "k.s", "k.u, k.d", 1, 10**9, f"k AS segment, {VALUE}", raw_below=5))
def slice_segment_week(spark, sf):
    """User-day digests of one week by market segment; raw and full digests mixed, all native."""
    e = ev(spark, sf).where("ts >= timestamp_ntz'2024-01-08' and ts < timestamp_ntz'2024-01-15'").withColumn("day", F.date_trunc("day", "ts").cast("timestamp_ntz"))
    d = summarize(e, ["user_id", "day"], "value", ORDER["events"], EXACT5).join(hierarchy(spark, sf), "user_id")
    return slice_quantiles(d, None, "true", ["segment"], FIVE).select("segment", "level", F.round("value", 7).alias("value"))


_CUBE = f"WITH {leaf_lists('SELECT user_id AS k, value AS x FROM events', FIVE)}, h AS (SELECT c_custkey AS u, c_mktsegment AS s, r_name AS r FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)"
_CUBE += ", ex AS (SELECT dg.k AS leaf, struct_pack(s := s, r := r) AS k FROM (SELECT DISTINCT k FROM dg) AS dg JOIN h ON h.u = dg.k UNION ALL SELECT dg.k, struct_pack(s := s, r := NULL) FROM (SELECT DISTINCT k FROM dg) AS dg JOIN h ON h.u = dg.k UNION ALL SELECT dg.k, struct_pack(s := NULL, r := r) FROM (SELECT DISTINCT k FROM dg) AS dg JOIN h ON h.u = dg.k UNION ALL SELECT dg.k, struct_pack(s := NULL, r := NULL) FROM (SELECT DISTINCT k FROM dg) AS dg JOIN h ON h.u = dg.k)"


@query(_CUBE + ",\n" + O.unrolled(FIVE, 1, 10**9, None, "SELECT struct_pack(s := coalesce(ex.k.s, '*'), r := coalesce(ex.k.r, '*')) AS k, 1 AS rn, dg.k AS cid, dg.n, dg.m, dg.p, dg.v FROM ex JOIN dg ON dg.k = ex.leaf") + f"\nSELECT k.s AS segment, k.r AS region, {VALUE} FROM kn_1")
def cube_segment_region(spark, sf):
    """All combinations of two dimensions, by expanding digests and not rows."""
    d = _user_digests(spark, sf, EXACT5).join(hierarchy(spark, sf), "user_id")
    each = lambda c: F.explode(F.array(F.col(c), F.lit("*")))
    wide = d.select(each("segment").alias("segment"), "region", "digest").select("segment", each("region").alias("region"), "digest")
    return rel.merge_one_blend(wide, ["segment", "region"], FIVE).select("segment", "region", "level", F.round("value", 7).alias("value"))


@query(rolled(_SUP, FIVE, _SUP_NATION, "k", 6, 3, "k AS s_nationkey, p AS level, round(exp(v), 7) AS value").replace("dg.v FROM od", "ln(dg.v) AS v FROM od"))
def merge_log(spark, sf):
    """Digest values blended on the log scale."""
    return flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", ["l_suppkey"], EXACT5.but(batch=3, scale="log")), ["s_nationkey"])


query(rolled(_SUP, FIVE, _SUP_NATION, "md5(CAST(k AS VARCHAR))", 6, 3, f"k AS s_nationkey, {VALUE}"), "order_random")(
    lambda spark, sf: flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", [F.md5(F.col("l_suppkey").cast("string"))], EXACT5.but(batch=3)), ["s_nationkey"])
)
query(rolled(_SUP, FIVE, _SUP_NATION, "(SELECT v FROM dg WHERE dg.k = ll.k AND dg.m = 2), k", 6, 3, f"k AS s_nationkey, {VALUE}"), "order_sorted")(
    lambda spark, sf: flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", [F.get("digest.vals", F.lit(2)), "l_suppkey"], EXACT5.but(batch=3)), ["s_nationkey"])
)
query("SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS parts, min(value) AS low, max(value) AS high FROM events GROUP BY event_type", "merge_salted")(
    lambda spark, sf: _facts(merge(_user_digests(spark, sf, EXACT, ("user_id", "event_type")), ["event_type"], "digest", ["user_id"], _S41, fan_in=40), "event_type")
)
query(rolled(_SUP, FIVE, "0", "k", 1, 10**9, VALUE), "merge_global")(
    lambda spark, sf: rel.global_blend(_supplier_digests(spark, sf), FIVE).select("level", F.round("value", 7).alias("value"))
)
query(rolled(_SUP, FIVE, _SUP_NATION, "k", 4, 4, f"k AS s_nationkey, {VALUE}"), "merge_batch_values")(
    lambda spark, sf: flat(merge(_supplier_digests(spark, sf), ["s_nationkey"], "digest", ["l_suppkey"], EXACT5.but(batch=20, batch_unit="values")), ["s_nationkey"])
)

# ---- grids, scales, extensions ----------------------------------------------------------------------------


def grid_values(df: DataFrame, keys: list[str], value: str, grid_id: str) -> DataFrame:
    """``keys, i, p, value``: the levels of a grid and what every group has there, by windows that spill.

    A step of the curve takes the levels that it holds; a level where one step ends and the next begins is taken by both.
    """
    at = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(float(p)).alias("p")) for i, p in enumerate(L.grid(grid_id).levels)])
    low, high = (lambda c: (c["p"] - SLACK) * F.col("total")), (lambda c: (c["p"] + SLACK) * F.col("total"))
    held = F.filter(at, lambda c: ((F.col("lo") < low(c)) & (low(c) <= F.col("hi"))) | ((F.col("lo") <= high(c)) & (high(c) < F.col("hi"))))
    steps = rel.step_cdf(df, keys, value).select(*keys, "x", F.explode(held).alias("c"))
    return steps.groupBy(*keys, "c.i", "c.p").agg(F.round((F.min("x") + F.max("x")) / 2, 7).alias("value")).withColumn("p", F.round("p", 9))


def _grid(name: str, grid_id: str, sql: str) -> None:
    """``sql`` gives ``(i, p)``; the values of every event type at these levels are read off its sorted list."""
    body = f"""WITH gr AS MATERIALIZED (SELECT i, CAST(p AS DOUBLE) AS p FROM ({sql}) AS y),
ll AS MATERIALIZED (SELECT event_type, count(*) AS n, list_sort(list(value)) AS a FROM events WHERE value IS NOT NULL AND NOT isnan(value) GROUP BY event_type)
SELECT event_type, i, round(p, 9) AS p, round(CASE WHEN p <= 0 THEN a[1] WHEN p >= 1 THEN a[n] ELSE (a[greatest(1, CAST(ceil(p * n - 1e-12 * n) AS BIGINT))] + a[least(n, CAST(floor(p * n + 1e-12 * n) AS BIGINT) + 1)]) / 2 END, 7) AS value FROM ll CROSS JOIN gr"""
    query(body, name)(lambda spark, sf: grid_values(ev(spark, sf), ["event_type"], "value", grid_id))


_ROUND_20 = "unnest([0, 0.001, 0.0015, 0.002, 0.003, 0.004, 0.006, 0.009, 0.0125, 0.018, 0.025, 0.035, 0.05, 0.075, 0.1, 0.14, 0.19, 0.25, 0.33, 0.41])"
_grid("grid_uniform", "uniform:41", "SELECT CAST(i AS INT) AS i, i / 40.0::DOUBLE AS p FROM range(41) AS t(i)")
_grid("grid_logit", "logit:100:0.0025", "SELECT CAST(i AS INT) AS i, CASE i WHEN 0 THEN 0 WHEN 99 THEN 1 ELSE 1 / (1 + exp(ln(0.9975 / 0.0025) - (i - 1) * 2 * ln(0.9975 / 0.0025) / 97)) END AS p FROM range(100) AS t(i)")
_grid("grid_round41", "round41", f"SELECT CAST(row_number() OVER (ORDER BY p) - 1 AS INT) AS i, p FROM (SELECT {_ROUND_20} AS p UNION ALL SELECT 0.5 UNION ALL SELECT 1 - {_ROUND_20}) AS z")
_grid("grid_focus", "focus:21:0.9:0.5", "SELECT CAST(row_number() OVER (ORDER BY p) - 1 AS INT) AS i, p FROM (SELECT min(p) AS p FROM (SELECT i / 10.0::DOUBLE AS p FROM range(11) AS t(i) UNION ALL SELECT 0.85 + (i + 1) * 0.1 / 11.0::DOUBLE FROM range(10) AS t(i)) AS y GROUP BY round(p, 9)) AS z")


def trained_levels(df: DataFrame, value: str, m: int, cells: int = 4096) -> np.ndarray:
    """Levels learnt from all values: counts and extremes of ``cells`` equal ranges between the exact extremes."""
    x = df.select(F.col(value).cast("double").alias("x")).where("x is not null and not isnan(x)")
    ends = x.agg(F.min("x").alias("low"), F.max("x").alias("high")).first()
    if ends.low is None or ends.low == ends.high:
        return L.uniform_levels(m)
    cell = F.least(F.floor((F.col("x") - ends.low) / (ends.high - ends.low) * cells), F.lit(cells - 1))
    got = x.groupBy(cell.alias("cell")).agg(F.min("x").alias("low"), F.max("x").alias("high"), F.count("*").alias("n")).collect()  # at most one row per cell
    low, high, n = (np.array(c) for c in zip(*[(r.low, r.high, r.n) for r in sorted(got, key=lambda r: r.cell)], strict=True))
    return L.train_levels_counts(low, high, n, m)


@query()
def grid_trained(spark, sf):
    """A grid learnt from the shape of all values, then used."""
    e = ev(spark, sf)
    return flat(summarize(e, ["event_type"], "value", ORDER["events"], Scheme(grid=L.list_grid(trained_levels(e, "value", 41)), batch=100)), ["event_type"])


query(None, "grid_adaptive")(lambda spark, sf: flat(summarize(ev(spark, sf), ["event_type"], "value", ORDER["events"], Scheme(batch=100, adapt=True)), ["event_type"]))
query(None, "grid_tails")(lambda spark, sf: flat(summarize(ev(spark, sf), ["event_type"], "value", ORDER["events"], Scheme(batch=100, tails=True)), ["event_type"]))
query(_leaf_sql(EV_RAW, "user_id", FIVE, 4, 30, decay=0.5), "decay")(lambda spark, sf: flat(_user_digests(spark, sf, Scheme(grid="five", report="five", batch=30, decay=0.5)), ["user_id"]))


@query()
def seed_hour_of_day(spark, sf):
    """Every hour of the last week starts from what that hour of the day looked like before."""
    return flat(X.seeded_by(ev(spark, sf), F.hour("ts"), F.to_date("ts"), "value", ORDER["events"], "2024-01-24", Scheme(batch=50)), ["part", "period"])


_DUR = " UNION ALL ".join(f"SELECT '{name}' AS duration, count(*) AS periods, CAST(sum(c) AS BIGINT) AS n FROM (SELECT count(*) AS c FROM events GROUP BY time_bucket(INTERVAL '{name}', ts, TIMESTAMP '1970-01-01')) AS z" for name in ("5 minutes", "1 hour", "1 day", "30 days"))


@query(_DUR)
def durations(spark, sf):
    """Summaries of chosen length."""
    out = None
    for d in ("5 minutes", "1 hour", "1 day", "30 days"):
        s = summarize(ev(spark, sf), [], "value", ORDER["events"], _S41, period=d, time="ts", engine="sorted")
        row = s.agg(F.count("*").alias("periods"), F.sum("digest.n").alias("n")).select(F.lit(d).alias("duration"), "periods", "n")
        out = row if out is None else out.unionAll(row)
    return out


query("SELECT l_suppkey, l_quantity AS atom, count(*) AS n FROM lineitem WHERE l_quantity IN (1, 2, 25, 50) GROUP BY ALL", "spikes_quantity")(
    lambda spark, sf: X.spike_counts(li(spark, sf), ["l_suppkey"], "l_quantity", [1.0, 2.0, 25.0, 50.0])
)


@query(f"""WITH {leaf_lists('SELECT l_suppkey AS k, l_discount AS x FROM lineitem', R11)} SELECT k AS l_suppkey, p AS level, round(v, 7) AS value FROM dg WHERE p IN (0.25, 0.5, 0.9)""")
def spikes_discount(spark, sf):
    """All values are known atoms, so recombining counters and an empty rest is exact."""
    return X.with_spikes(li(spark, sf), ["l_suppkey"], "l_discount", ORDER["lineitem"], [k / 100 for k in range(11)], LEVELS, Scheme(batch=100)).withColumn("value", F.round("value", 7))


# ---- baselines --------------------------------------------------------------------------------------------


def _quant_sql(fn: str, key: str = "event_type", src: str = "events", value: str = "value") -> str:
    return " UNION ALL ".join(f"SELECT {key}, CAST({p} AS DOUBLE) AS level, round({fn}({value}, {p}), 7) AS value FROM {src} GROUP BY {key}" for p in L.TABLE_6)


T6 = list(L.TABLE_6)
_r4 = lambda df: df.withColumn("value", F.round("value", 7))
query(_quant_sql("quantile_disc"), "exact_disc")(lambda spark, sf: _r4(B.exact_quantiles(ev(spark, sf), ["event_type"], "value", T6)))
query(_quant_sql("quantile_cont"), "exact_cont")(lambda spark, sf: _r4(B.exact_quantiles(ev(spark, sf), ["event_type"], "value", T6, "cont")))
query(_quant_sql("quantile_disc"), "exact_disc_windows")(lambda spark, sf: _r4(B.exact_quantiles(ev(spark, sf), ["event_type"], "value", T6, "disc", "windows")))
query(_quant_sql("quantile_cont"), "exact_cont_windows")(lambda spark, sf: _r4(B.exact_quantiles(ev(spark, sf), ["event_type"], "value", T6, "cont", "windows")))
query(f"""WITH {leaf_lists('SELECT event_type AS k, value AS x FROM events', T6)} SELECT k AS event_type, p AS level, round(v, 7) AS value FROM dg""", "exact_mid")(
    lambda spark, sf: _r4(B.exact_quantiles(ev(spark, sf), ["event_type"], "value", T6, "mid"))
)
query("SELECT event_type, count(value) AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd FROM events GROUP BY event_type", "moments")(
    lambda spark, sf: B.moments(ev(spark, sf), ["event_type"], "value").select("event_type", "n", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"))
)
from statistics import NormalDist  # noqa: E402

query(" UNION ALL ".join(f"SELECT event_type, CAST({p} AS DOUBLE) AS level, round(avg(value) + stddev_samp(value) * {NormalDist().inv_cdf(p)!r}, 7) AS value FROM events GROUP BY event_type" for p in T6), "normal_fit")(
    lambda spark, sf: _r4(B.normal_fit_quantiles(ev(spark, sf), ["event_type"], "value", T6))
)
_BY_TYPE = "SELECT event_type AS k, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) AS rn, value AS x FROM events WHERE value IS NOT NULL"
for _name, _weight in (("sa_basic", None), ("sa_ewma", 0.02)):
    query(f"SELECT k AS event_type, n, level, round(value, 7) AS value FROM ({O.tracker(_BY_TYPE, 0.9, _weight)}) AS z", _name)(
        lambda spark, sf, weight=_weight: _r4(B.stochastic_quantile(ev(spark, sf), ["event_type"], "value", ORDER["events"], 0.9, weight=weight))
    )
query("SELECT CAST(0.9 AS DOUBLE) AS level, quantile_disc(value, 0.9) AS value FROM events", "multipass_select")(lambda spark, sf: B.multipass_select(ev(spark, sf), "value", 0.9, memory=500).select("level", "value"))
for _name, _levels in (("bracket_one", [0.9]), ("bracket_many", T6)):
    query(f"SELECT k AS event_type, level, value FROM ({O.brackets(_BY_TYPE, _levels)}) AS z", _name)(
        lambda spark, sf, levels=_levels: B.bracket_buffers(ev(spark, sf), ["event_type"], "value", ORDER["events"], levels)
    )
query(None, "rank_sketch")(lambda spark, sf: B.rank_sketch(ev(spark, sf), ["event_type"], "value", T6))
query(None, "kll")(lambda spark, sf: B.kll(ev(spark, sf), ["event_type"], "value", T6))
query(f"""WITH {leaf_lists(_SUP, FIVE)} SELECT s_nationkey, p AS level, round(sum(n * v) / sum(n), 7) AS value FROM dg JOIN supplier ON s_suppkey = dg.k WHERE p IN (0.25, 0.5, 0.75) GROUP BY s_nationkey, p""", "naive_mean_quantile")(
    lambda spark, sf: _r4(B.mean_of_quantiles(_supplier_digests(spark, sf), ["s_nationkey"], [0.25, 0.5, 0.75]))
)
query("SELECT user_id, value FROM (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY md5('r|' || event_id)) AS r FROM events) AS z WHERE r <= 11", "reservoir")(
    lambda spark, sf: B.reservoir(ev(spark, sf), ["user_id"], "value", ["event_id"])
)

# ---- measures ---------------------------------------------------------------------------------------------
@query(" UNION ALL ".join(f"SELECT CAST({p} AS DOUBLE) AS level, round(sqrt({p} * (1 - {p}) / count(value)) * (quantile_cont(value, least({p} + 0.01, 1)) - quantile_cont(value, {p} - 0.01)) / (least({p} + 0.01, 1) - ({p} - 0.01)), 6) AS se FROM events" for p in T6))
def tab1_se(spark, sf):
    return A.asymptotic_se(ev(spark, sf), "value", T6).withColumn("se", F.round("se", 6))


query("SELECT 82 AS values_held", "memory_values")(lambda spark, sf: most_held(ev(spark, sf), "value", Scheme(grid="uniform:41", batch=41)))
query("SELECT user_id, count(*) AS n, count(*) // 41 AS full_flushes, count(*) % 41 AS rest FROM events GROUP BY user_id", "flush_count")(lambda spark, sf: A.flush_counts(ev(spark, sf), ["user_id"], "value", 41))
query("SELECT CAST(sum(n) * 8 AS BIGINT) AS raw_bytes, CAST(sum(least(n, 11) + 1) * 8 AS BIGINT) AS digest_bytes, count(*) AS digests FROM (SELECT count(*) AS n FROM events GROUP BY user_id, event_type) AS z", "bytes_raw_vs_digest")(
    lambda spark, sf: A.bytes_moved(_user_digests(spark, sf, _S41, ("user_id", "event_type")))
)
query(f"""WITH {leaf_lists('SELECT user_id AS k, value AS x FROM events', R11)} SELECT dg.k AS user_id, p AS level, round(v, 7) AS value, round(abs((SELECT avg(CASE WHEN e.value <= dg.v + 1e-9 * abs(dg.v) THEN 1.0 ELSE 0.0 END) FROM events AS e WHERE e.user_id = dg.k) - p), 9) AS rank_error FROM dg""", "rank_error")(
    lambda spark, sf: A.rank_error(R.long(_user_digests(spark, sf), ["user_id"], digits=None), ev(spark, sf), ["user_id"], "value").select("user_id", "level", F.round("value", 7).alias("value"), F.round("rank_error", 9).alias("rank_error"))
)
query("SELECT source, round(quantile_disc(n_chars, 0.99) / quantile_disc(n_chars, 0.01), 6) AS spread FROM documents GROUP BY source", "spread_ratio")(
    lambda spark, sf: A.spread_ratio(B.exact_quantiles(table(spark, sf, "documents"), ["source"], "n_chars", [0.01, 0.99]), ["source"]).withColumn("spread", F.round("spread", 6))
)


_MD5, _MEDIAN = "md5(CAST(k AS VARCHAR))", "(SELECT v FROM dg WHERE dg.k = ll.k AND dg.m = 2)"
_TWO = [rolled(_SUP, FIVE, _SUP_NATION, order, 6, 3, "k AS s_nationkey, p AS level, round(v, 6) AS value") for order in (_MD5, _MEDIAN)]


@query(f"SELECT round(max(abs(a.value - b.value)), 6) AS max_gap, round(max(abs(a.value - b.value) / nullif(abs(a.value), 0)), 9) AS max_relative, count(*) AS cells FROM ({_TWO[0]}) AS a JOIN ({_TWO[1]}) AS b USING (s_nationkey, level)")
def order_gap(spark, sf):
    """Random against sorted arrival of supplier digests, at a small batch."""
    s = EXACT5.but(batch=3)
    d = _supplier_digests(spark, sf)
    a = R.long(merge(d, ["s_nationkey"], "digest", [F.md5(F.col("l_suppkey").cast("string"))], s), ["s_nationkey"])
    b = R.long(merge(d, ["s_nationkey"], "digest", [F.get("digest.vals", F.lit(2)), "l_suppkey"], s), ["s_nationkey"])
    return A.order_gap(a, b, ["s_nationkey"]).withColumns({"max_gap": F.round("max_gap", 6), "max_relative": F.round("max_relative", 9)})


@query("SELECT date_trunc('day', ts) AS day, count(*) AS n, count(DISTINCT date_trunc('hour', ts)) AS parts, min(value) AS low, max(value) AS high FROM events WHERE ts >= TIMESTAMP '2024-01-05' AND ts < TIMESTAMP '2024-01-20' GROUP BY ALL")
def planned_slice(spark, sf):
    """A request by day: the planner reads the hour tier and not the user-hour tier, and derives the day."""
    from .planner import Tier, answer

    e = ev(spark, sf).withColumn("hour", F.date_trunc("hour", "ts").cast("timestamp_ntz"))
    tiers = [
        Tier("user_hour", ("user_id", "hour"), 100_000, lambda: _user_hours(spark, sf, _S41)),
        Tier("hour", ("hour",), 720, lambda: summarize(e, ["hour"], "value", ORDER["events"], _S41)),
        Tier("user", ("user_id",), 1_500, lambda: _user_digests(spark, sf, _S41)),
    ]
    return _facts(answer(tiers, ["day"], "day >= timestamp_ntz'2024-01-05' and day < timestamp_ntz'2024-01-20'", scheme=_S41), "day")
