"""Queries whose SQL unrolls a fixed number of flushes, on tables that need more, beside the same SQL with as many as they need."""

import sys
from pathlib import Path

import duckdb
import pytest

import cdfblend.plans

sys.path.insert(0, str(Path(__file__).resolve().parents[1] / "tools"))
from verify import rows_of  # noqa: E402

from cdfblend import oracles as O  # noqa: E402
from cdfblend.plans import methods as M  # noqa: E402
from cdfblend.plans import workloads as W  # noqa: E402

REG = cdfblend.plans.load()
SF = "/root/testdata/sf0.01"
FIVE, R11, VALUE = M.FIVE, M.R11, M.VALUE
_USERS = "SELECT user_id AS k, value AS x FROM events"
_NATION = "(SELECT n_name FROM customer JOIN nation ON n_nationkey = c_nationkey WHERE c_custkey = ll.k)"
_REGION = "(SELECT r_name FROM nation JOIN region ON r_regionkey = n_regionkey WHERE n_name = leaf)"


def _suppliers(flushes, batch, order="k", select=f"k AS s_nationkey, {VALUE}"):
    return M.rolled(M._SUP, FIVE, M._SUP_NATION, order, flushes, batch, select)


def _gap(flushes, ties=""):
    """The SQL of ``order_gap`` with other flushes, and with ties of the median in an order that it leaves open."""
    sql = REG.ORACLES["order_gap"]
    for order, more in ((M._MD5, ""), (M._MEDIAN, ties)):
        select = "k AS s_nationkey, p AS level, round(v, 6) AS value"
        sql = sql.replace(_suppliers(6, 3, order, select), _suppliers(flushes, 3, order + more, select))
    return sql


def _regions(flushes):
    nations = M.rolled(_USERS, FIVE, _NATION, "k", flushes, 5, "k AS leaf, w AS n, m, p, v")
    return M.tier_sql(nations, _REGION, "leaf", 3, 2, f"k AS region, CAST(w AS BIGINT) AS n, {VALUE}")


_BY_MEDIAN = "(SELECT v FROM dg WHERE dg.k = ll.k AND dg.m = 2), k"
_MOST = "SELECT max(c) FROM (SELECT count(*) AS c FROM {} GROUP BY {})".format
_SUPPLIERS, _CUSTOMERS = _MOST("supplier", "s_nationkey"), _MOST("(SELECT DISTINCT user_id, c_nationkey FROM events JOIN customer ON c_custkey = user_id)", "c_nationkey")
#: Flushes of the registered SQL, records of a flush, SQL of the most records that a key has, the SQL by flushes.
TEXTS = {
    "hier_nation_tier": (4, 5, _CUSTOMERS, lambda f: M.rolled(_USERS, FIVE, _NATION, "k", f, 5, f"k AS nation, {VALUE}")),
    "hier_user_nation_region": (16, 5, _CUSTOMERS, _regions),
    "inhomog_sorted": (4, 25, "SELECT count(*) FROM supplier", lambda f: M.rolled(W._FAR, FIVE, "0", _BY_MEDIAN, f, 25, VALUE)),
    "inhomog_suppliers": (4, 25, "SELECT count(*) FROM supplier", lambda f: M.rolled(W._FAR, FIVE, "0", "k", f, 25, VALUE)),
    "leaf_log": (3, 20, _MOST("documents", "source"), lambda f: M._leaf_sql(M._LOG_RAW, "source", FIVE, f, 20, "p AS level, round(exp(v), 7) AS value")),
    "leaf_resume": (5, 20, _MOST("events", "user_id"), lambda f: M._leaf_sql(M.EV_RAW, "user_id", R11, f, 20)),
    "leaf_slog": (4, 25, _MOST("customer", "c_nationkey"), lambda f: M._leaf_sql(M._SLOG_RAW, "c_nationkey", FIVE, f, 25, "p AS level, round(sign(v) * (exp(abs(v)) - 1), 7) AS value")),
    "merge_batch_values": (4, 4, _SUPPLIERS, lambda f: _suppliers(f, 4)),
    "merge_log": (6, 3, _SUPPLIERS, lambda f: _suppliers(f, 3, "k", "k AS s_nationkey, p AS level, round(exp(v), 7) AS value").replace("dg.v FROM od", "ln(dg.v) AS v FROM od")),
    "merge_mixed": (3, 60, "SELECT count(DISTINCT user_id) FROM events", lambda f: M.rolled(M._UT, R11, "k.t", "k.u", f, 60, f"k AS event_type, {VALUE}", raw_below=11)),
    "merge_suppliers": (6, 3, _SUPPLIERS, lambda f: _suppliers(f, 3)),
    "order_gap": (6, 3, _SUPPLIERS, lambda f: _gap(f, ", k")),
}


def write(con, sf, **tables):
    for name, sql in tables.items():
        con.execute(f"COPY ({sql}) TO '{sf}/{name}.parquet' (FORMAT parquet)")
        con.execute(f"CREATE OR REPLACE VIEW {name} AS SELECT * FROM '{sf}/{name}.parquet'")


def rows(con, sql):
    rel = con.execute(sql)
    return rows_of([d[0] for d in rel.description], rel.fetchall())


def got(spark, sf, name):
    df = REG.QUERIES[name](spark, str(sf))
    return rows_of(df.columns, df.collect())


@pytest.fixture(scope="module")
def large(tmp_path_factory):
    """Tables of sf0.01 with twice the suppliers and users, few nations and sources, more events of some users."""
    sf, con = tmp_path_factory.mktemp("large"), duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        con.execute(f"CREATE VIEW old_{p.stem} AS SELECT * FROM '{p}'")
    twice = "(SELECT unnest([0, 1]) AS c) AS copies"
    write(
        con, sf,
        region="SELECT * FROM old_region", nation="SELECT * FROM old_nation",
        supplier=f"SELECT * REPLACE (s_suppkey + c * 100000 AS s_suppkey, CAST(s_nationkey % 3 AS INT) AS s_nationkey) FROM old_supplier, {twice}",
        customer=f"SELECT * REPLACE (c_custkey + c * 100000 AS c_custkey, CAST(c_nationkey % 3 AS INT) AS c_nationkey) FROM old_customer, {twice}",
        lineitem=f"SELECT * REPLACE (l_suppkey + c * 100000 AS l_suppkey, l_orderkey + c * 10000000 AS l_orderkey, l_extendedprice * (1 + 0.1::DOUBLE * c) AS l_extendedprice) FROM old_lineitem, {twice}",
        events=f"SELECT * REPLACE (user_id + (CASE WHEN user_id % 3 = 0 THEN 0 ELSE c * 100000 END) AS user_id, event_id + c * 10000000 AS event_id, value * (1 + 0.1::DOUBLE * c) AS value) FROM old_events, {twice}",
        documents="SELECT * REPLACE (concat('s', doc_id % 4) AS source) FROM old_documents",
    )
    return sf, con


@pytest.mark.parametrize("name", sorted(TEXTS))
def test_beyond_the_flushes_of_the_sql(spark, large, name):
    sf, con = large
    flushes, batch, most, text = TEXTS[name]
    assert (_gap(flushes) if name == "order_gap" else text(flushes)) == REG.ORACLES[name]
    need = -(-con.execute(most).fetchall()[0][0] // batch)
    assert need > flushes
    whole = rows(con, text(need))
    assert got(spark, sf, name) == whole != rows(con, REG.ORACLES[name])


def test_order_gap_breaks_ties_of_the_median_by_supplier(spark, tmp_path):
    """Fifteen suppliers of a nation share one median and differ elsewhere, so that the gap depends on the order among them."""
    con = duckdb.connect()
    write(
        con, tmp_path,
        supplier="SELECT CAST(s AS BIGINT) AS s_suppkey, 'S' AS s_name, CAST(s % 20 AS INT) AS s_nationkey, 0.0::DOUBLE AS s_acctbal FROM range(1, 301) AS t(s)",
        lineitem="""SELECT CAST(s * 10 + i AS BIGINT) AS l_orderkey, CAST(1 AS BIGINT) AS l_partkey, CAST(s AS BIGINT) AS l_suppkey, CAST(i AS INT) AS l_linenumber, 1.0::DOUBLE AS l_quantity,
            CAST(1000 + (i - 3) * (1 + s * s * 7 % 101) AS DOUBLE) AS l_extendedprice, 0.0::DOUBLE AS l_discount, 0.0::DOUBLE AS l_tax, 'N' AS l_returnflag, 'O' AS l_linestatus, TIMESTAMP '2024-01-01' AS l_shipdate
            FROM range(1, 301) AS t(s), range(1, 6) AS u(i)""",
    )
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")  # suppliers arrive from several tasks
    try:
        assert got(spark, tmp_path, "order_gap") == rows(con, _gap(6, ", k"))
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


@pytest.mark.parametrize(("name", "tier"), [("fig7_series", "hour"), ("fig8_series", "day")])
def test_hours_of_more_than_a_hundred_users(spark, monkeypatch, name, tier):
    """Hours of the largest tables take two flushes of a hundred users; the SQL puts all users of an hour into one."""
    sf, con = "/root/testdata/sf0.1", duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    most, least, cell = con.execute("SELECT max(u), min(n), max(c) FROM (SELECT count(*) AS u, sum(c) AS n, max(c) AS c FROM (SELECT date_trunc('hour', ts) AS h, user_id, count(*) AS c FROM events GROUP BY ALL) AS z GROUP BY h) AS y").fetchall()[0]
    assert 100 < most <= 200 and least >= len(R11) > cell  # no hour is raw, every user-hour is
    registered = REG.ORACLES[name]
    assert W._rounded(tier) == registered[: len(W._rounded(tier))]
    users = "SELECT date_trunc('hour', ts) AS k, dense_rank() OVER (PARTITION BY date_trunc('hour', ts) ORDER BY user_id) AS rn, ln(1 + value) AS x FROM events"
    knots = f"WITH {O.unrolled(W.U100, 2, 100, users)}\nSELECT k, w AS n, m, p, v FROM kn_2"
    monkeypatch.setattr(W, "_FULL_HOURS", f"WITH {O.read_out(R11, knots)}\nSELECT k, w AS n, m, p, v FROM kn_1")
    whole = rows(con, W._rounded(tier) + registered[registered.rindex(") AS z") + len(") AS z") :])
    assert got(spark, sf, name) == whole != rows(con, registered)
