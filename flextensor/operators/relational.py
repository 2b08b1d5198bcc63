"""Relational operators around the tensor methods, each with its SQL twin (None: rows only)."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sampling import MODULUS, portable_hash, portable_hash_sql
from ..sources import tables
from ..sources.tables import load_table

Query = Callable[[SparkSession, str], DataFrame]
TABLE: dict[str, tuple[Query, str | None]] = {}


def query(name: str, sql: str | None):
    def add(f: Query) -> Query:
        TABLE[name] = (f, sql)
        return f

    return add


def K():  # noqa: N802
    return F.get_json_object("props", "$.k").cast("long")

K_SQL = "CAST(json_extract_string(props, '$.k') AS BIGINT)"
long = lambda c: c.cast("long")


def ev(spark, d, *cols):
    return load_table(spark, d, "events", list(cols) or None)


def li(spark, d, *cols):
    return load_table(spark, d, "lineitem", list(cols) or None)


@query("q_scan_parquet", "SELECT l_orderkey, l_suppkey, l_quantity FROM lineitem WHERE l_quantity > 45")
def _(spark, d):
    return li(spark, d, "l_orderkey", "l_suppkey", "l_quantity").where("l_quantity > 45")


def coordinates(spark, d):
    return ev(spark, d, "user_id", "ts", "props").select("user_id", long(F.hour("ts")).alias("hr"), K().alias("k")).groupBy("user_id", "hr", "k").agg(F.count("*").alias("n"))


COORD_SQL = f"SELECT user_id, CAST(hour(ts) AS BIGINT) AS hr, {K_SQL} AS k, count(*) AS n FROM events GROUP BY ALL"
for _fmt in ("csv", "json", "orc"):
    TABLE[f"q_scan_{_fmt}"] = ((lambda f: lambda spark, d: tables.round_trip(coordinates(spark, d), f))(_fmt), COORD_SQL)


@query("q_sink_partitioned", "SELECT event_id, user_id FROM events WHERE CAST(ts AS DATE) = DATE '2024-01-02'")
def _(spark, d):
    path = tables.scratch(spark, "days")
    tables.write_by_day(ev(spark, d, "event_id", "user_id", "ts"), "ts", path)
    return tables.read_day(spark, path, "2024-01-02").select("event_id", "user_id")


@query("q_sink_model", "SELECT CAST(1 AS INTEGER) AS mode, i AS idx, round(sin(0.7 * i + 1), 9) AS f FROM range(50) t(i)")
def _(spark, d):
    import numpy as np

    from ..functions.kernels import Kernel
    from ..model import ModelState, load_model, save_model

    path = tables.scratch(spark, "model")
    save_model(spark, ModelState((np.sin(0.7 * np.arange(50) + 1)[:, None],), np.zeros((2, 1)), Kernel("rbf", [1.0])), path)
    u = load_model(spark, path).factors[0]
    return spark.createDataFrame([(1, i, round(float(x[0]), 9)) for i, x in enumerate(u)], "mode int, idx long, f double")


@query("q_project_modes", f"SELECT event_id, CAST(hour(ts) AS BIGINT) AS hr, CAST(minute(ts) AS BIGINT) AS mi, CAST(year(ts) * 12 + month(ts) AS BIGINT) AS mo, {K_SQL} % 10 AS fold FROM events")
def _(spark, d):
    return ev(spark, d, "event_id", "ts", "props").select("event_id", long(F.hour("ts")).alias("hr"), long(F.minute("ts")).alias("mi"), long(F.year("ts") * 12 + F.month("ts")).alias("mo"), F.pmod(K(), F.lit(10)).alias("fold"))


@query("q_filter_pred", "SELECT event_id FROM events WHERE event_type IN ('click', 'view') AND value BETWEEN 10 AND 50 AND regexp_matches(event_type, '^c') AND value IS NOT NULL AND NOT isnan(value)")
def _(spark, d):
    e = ev(spark, d, "event_id", "event_type", "value")
    return e.where(F.col("event_type").isin("click", "view") & F.col("value").between(10, 50) & F.col("event_type").rlike("^c") & F.col("value").isNotNull() & ~F.isnan("value")).select("event_id")


@query("q_case", "SELECT event_id, CASE WHEN event_type = 'click' THEN 1 ELSE 0 END AS y FROM events")
def _(spark, d):
    return ev(spark, d, "event_id", "event_type").select("event_id", F.when(F.col("event_type") == "click", 1).otherwise(0).alias("y"))


@query("q_join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark, d):
    # nation has 25 rows at every scale
    return load_table(spark, d, "customer", ["c_nationkey"]).join(F.broadcast(load_table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


JOIN_SQL = "SELECT o_custkey, count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"
for _name, _hint in (("q_join_smj", "merge"), ("q_join_shuffle_hash", "shuffle_hash")):
    TABLE[_name] = (
        (lambda h: lambda spark, d: li(spark, d, "l_orderkey", "l_linenumber").join(load_table(spark, d, "orders", ["o_orderkey", "o_custkey"]).hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("s")))(_hint),
        JOIN_SQL,
    )


@query("q_join_left", "SELECT c_custkey, coalesce(f, 0) AS f, f IS NULL AS cold FROM customer LEFT JOIN (SELECT o_custkey, CAST(count(*) AS DOUBLE) AS f FROM orders WHERE o_custkey % 3 = 0 GROUP BY o_custkey) ON c_custkey = o_custkey")
def _(spark, d):
    f = load_table(spark, d, "orders", ["o_custkey"]).where("o_custkey % 3 = 0").groupBy("o_custkey").agg(F.count("*").cast("double").alias("f"))
    return load_table(spark, d, "customer", ["c_custkey"]).join(f, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("f", F.lit(0.0)).alias("f"), F.col("f").isNull().alias("cold"))


DAY_SQL = "SELECT DISTINCT user_id FROM events WHERE event_type = 'click' AND CAST(ts AS DATE) = DATE '2024-01-0{}'"


def day_users(spark, d, day):
    return ev(spark, d, "user_id", "ts", "event_type").where((F.col("event_type") == "click") & (F.to_date("ts") == F.lit(f"2024-01-0{day}").cast("date"))).select("user_id").distinct()


@query("q_join_full", f"SELECT coalesce(a.user_id, b.user_id) AS user_id, a.user_id IS NOT NULL AS in_t, b.user_id IS NOT NULL AS in_next FROM ({DAY_SQL.format(1)}) a FULL JOIN ({DAY_SQL.format(2)}) b ON a.user_id = b.user_id")
def _(spark, d):
    a, b = day_users(spark, d, 1).select(F.col("user_id").alias("a")), day_users(spark, d, 2).select(F.col("user_id").alias("b"))
    return a.join(b, F.col("a") == F.col("b"), "full_outer").select(F.coalesce("a", "b").alias("user_id"), F.col("a").isNotNull().alias("in_t"), F.col("b").isNotNull().alias("in_next"))


@query("q_semi", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE EXISTS (SELECT 1 FROM supplier WHERE s_suppkey = l_suppkey AND s_nationkey < 5)")
def _(spark, d):
    return li(spark, d, "l_orderkey", "l_linenumber", "l_suppkey").join(load_table(spark, d, "supplier", ["s_suppkey", "s_nationkey"]).where("s_nationkey < 5"), F.col("l_suppkey") == F.col("s_suppkey"), "left_semi").select("l_orderkey", "l_linenumber")


@query("q_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def _(spark, d):
    return load_table(spark, d, "customer", ["c_custkey"]).join(load_table(spark, d, "orders", ["o_custkey", "o_totalprice"]).where("o_totalprice > 200000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("q_cross", "SELECT r_regionkey, n_nationkey FROM region, nation")
def _(spark, d):
    # 5 × 25 rows at every scale
    return load_table(spark, d, "region", ["r_regionkey"]).crossJoin(load_table(spark, d, "nation", ["n_nationkey"]))


@query("q_theta", "SELECT a.n_nationkey AS j, b.n_nationkey AS l FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
def _(spark, d):
    n = load_table(spark, d, "nation", ["n_nationkey"])
    a, b = n.select(F.col("n_nationkey").alias("j")), n.select(F.col("n_nationkey").alias("l"))
    return a.join(F.broadcast(b), F.col("j") < F.col("l"))


@query("q_range_join", "SELECT day, count(*) AS n FROM events JOIN (SELECT i AS day, TIMESTAMP '2024-01-01' + i * INTERVAL 1 DAY AS lo, TIMESTAMP '2024-01-02' + i * INTERVAL 1 DAY AS hi FROM range(31) t(i)) ON ts >= lo AND ts < hi GROUP BY day")
def _(spark, d):
    start = F.lit("2024-01-01 00:00:00").cast("timestamp_ntz")
    days = spark.range(31).select(F.col("id").alias("day"), (start + F.make_dt_interval("id")).alias("lo"), (start + F.make_dt_interval(F.col("id") + 1)).alias("hi"))
    return ev(spark, d, "ts").join(F.broadcast(days), (F.col("ts") >= F.col("lo")) & (F.col("ts") < F.col("hi"))).groupBy("day").agg(F.count("*").alias("n"))


@query("q_interval_join", "SELECT a.event_id AS view_id, b.event_id AS click_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def _(spark, d):
    from ..streaming.events import views_to_clicks

    return views_to_clicks(ev(spark, d, "event_id", "user_id", "event_type", "ts")).select("view_id", "click_id")


@query("q_asof", "SELECT event_id, CAST(max(v) AS BIGINT) AS version FROM events JOIN (SELECT i AS v, TIMESTAMP '2024-01-01' + i * INTERVAL 6 HOUR AS since FROM range(200) t(i)) ON since <= ts GROUP BY event_id")
def _(spark, d):
    """The last version not later than the event: both sides in one stream by time, the version carried forward inside days so that no window spans the table."""
    versions = spark.range(200).select(F.col("id").alias("v"), (F.lit("2024-01-01 00:00:00").cast("timestamp_ntz") + F.make_dt_interval(F.lit(0), (F.col("id") * 6).cast("int"))).alias("ts"))
    both = ev(spark, d, "event_id", "ts").withColumn("v", F.lit(None).cast("long")).unionByName(versions.withColumn("event_id", F.lit(None).cast("long")))
    both = both.withColumn("day", F.to_date("ts"))
    first = versions.groupBy(F.to_date("ts").alias("day")).agg(F.min("v").alias("first"))
    w = Window.partitionBy("day").orderBy(F.col("ts"), F.col("event_id").isNotNull())
    got = both.withColumn("last", F.last("v", ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    last_of_all = versions.agg(F.max("v").alias("end"))
    out = got.where("event_id is not null").join(F.broadcast(first), "day", "left").crossJoin(F.broadcast(last_of_all))
    return out.select("event_id", F.coalesce("last", F.when(F.col("first").isNull(), F.col("end")), F.col("first") - 1).alias("version")).where("version >= 0")


@query("q_agg_merge", f"SELECT user_id, {K_SQL} AS k, round(sum(value), 4) AS s, count(*) AS n, round(avg(value), 6) AS a, max(value) AS m FROM events GROUP BY ALL")
def _(spark, d):
    return ev(spark, d, "user_id", "value", "props").groupBy("user_id", K().alias("k")).agg(F.round(F.sum("value"), 4).alias("s"), F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("a"), F.max("value").alias("m"))


@query("q_agg_sort", "SELECT l_suppkey, max(l_returnflag || l_linestatus) AS hi, min(l_returnflag || l_linestatus) AS lo FROM lineitem GROUP BY l_suppkey")
def _(spark, d):
    s = F.concat("l_returnflag", "l_linestatus")
    return li(spark, d, "l_suppkey", "l_returnflag", "l_linestatus").groupBy("l_suppkey").agg(F.max(s).alias("hi"), F.min(s).alias("lo"))


@query("q_agg_distinct", "SELECT count(DISTINCT l_suppkey) AS d1, count(DISTINCT l_partkey) AS d2 FROM lineitem")
def _(spark, d):
    return li(spark, d, "l_suppkey", "l_partkey").agg(F.count_distinct("l_suppkey").alias("d1"), F.count_distinct("l_partkey").alias("d2"))


@query("q_agg_approx", "SELECT count(DISTINCT l_suppkey) AS d1, count(DISTINCT l_partkey) AS d2, true AS near FROM lineitem")
def _(spark, d):
    """Exact sizes, and whether the approximate ones are within 5 %."""
    exact = [F.count_distinct(c) for c in ("l_suppkey", "l_partkey")]
    near = [F.abs(F.approx_count_distinct(c, 0.02) - x) <= 0.05 * x for c, x in zip(("l_suppkey", "l_partkey"), exact, strict=True)]
    return li(spark, d, "l_suppkey", "l_partkey").agg(exact[0].alias("d1"), exact[1].alias("d2"), (near[0] & near[1]).alias("near"))


@query("q_agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS med FROM events GROUP BY event_type")
def _(spark, d):
    return ev(spark, d, "event_type", "value").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("med"))


@query("q_agg_stats", "SELECT round(avg(l_quantity), 4) AS a, round(stddev(l_quantity), 4) AS s, round(corr(l_quantity, l_extendedprice), 4) AS c FROM lineitem")
def _(spark, d):
    return li(spark, d, "l_quantity", "l_extendedprice").agg(F.round(F.avg("l_quantity"), 4).alias("a"), F.round(F.stddev("l_quantity"), 4).alias("s"), F.round(F.corr("l_quantity", "l_extendedprice"), 4).alias("c"))


@query("q_agg_collect", "SELECT l_suppkey % 10 AS block, array_to_string(list_sort(list(DISTINCT l_partkey % 50)), ',') AS parts FROM lineitem GROUP BY 1")
def _(spark, d):
    return li(spark, d, "l_suppkey", "l_partkey").groupBy((F.col("l_suppkey") % 10).alias("block")).agg(F.array_join(F.sort_array(F.collect_set(F.col("l_partkey") % 50)), ",").alias("parts"))


@query("q_agg_filter", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type <> 'click') AS rest FROM events GROUP BY user_id")
def _(spark, d):
    return ev(spark, d, "user_id", "event_type").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.sum(F.when(F.col("event_type") != "click", 1).otherwise(0)).alias("rest"))


TYPES = ["view", "signup", "error", "click", "purchase"]


@query("q_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS n_{t}" for t in TYPES) + " FROM events GROUP BY user_id")
def _(spark, d):
    p = ev(spark, d, "user_id", "event_type").groupBy("user_id").pivot("event_type", TYPES).count()
    return p.select("user_id", *(F.coalesce(F.col(t), F.lit(0)).alias(f"n_{t}") for t in TYPES))


@query("q_unpivot", "SELECT mode, idx, count(*) AS n FROM (SELECT 'i_1' AS mode, l_suppkey AS idx FROM lineitem UNION ALL SELECT 'i_2', l_partkey FROM lineitem) GROUP BY mode, idx")
def _(spark, d):
    return li(spark, d, "l_suppkey", "l_partkey").select(F.col("l_suppkey").alias("i_1"), F.col("l_partkey").alias("i_2")).unpivot([], ["i_1", "i_2"], "mode", "idx").groupBy("mode", "idx").agg(F.count("*").alias("n"))


_GS = "SELECT l_suppkey, l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_suppkey), (l_returnflag, l_linestatus), ())"


@query("q_grouping_sets", _GS)
def _(spark, d):
    li(spark, d).createOrReplaceTempView("ft_lineitem")
    return spark.sql(_GS.replace("FROM lineitem", "FROM ft_lineitem"))


@query("q_cube", "SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS n, CAST(grouping(l_returnflag, l_linestatus, l_linenumber) AS BIGINT) AS g FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus, l_linenumber)")
def _(spark, d):
    return li(spark, d, "l_returnflag", "l_linestatus", "l_linenumber").cube("l_returnflag", "l_linestatus", "l_linenumber").agg(F.count("*").alias("n"), long(F.grouping_id()).alias("g"))


@query("q_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def _(spark, d):
    n = load_table(spark, d, "nation").join(F.broadcast(load_table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return load_table(spark, d, "customer", ["c_nationkey"]).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("q_having", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id HAVING count(*) >= 60")
def _(spark, d):
    return ev(spark, d, "user_id").groupBy("user_id").agg(F.count("*").alias("n")).where("n >= 60")


@query("q_win_rownum", "SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events")
def _(spark, d):
    return ev(spark, d, "event_id", "user_id", "ts").select("event_id", long(F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).alias("rn"))


@query("q_win_rank", "SELECT event_id, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, ntile(4) OVER (PARTITION BY user_id ORDER BY value, event_id) AS q FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("value")
    return ev(spark, d, "event_id", "user_id", "value").select("event_id", long(F.rank().over(w)).alias("r"), long(F.dense_rank().over(w)).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), long(F.ntile(4).over(Window.partitionBy("user_id").orderBy("value", "event_id"))).alias("q"))


@query("q_win_lag", "SELECT event_id, round(value - lag(value) OVER w, 6) AS back, round(lead(value) OVER w - value, 6) AS ahead FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return ev(spark, d, "event_id", "user_id", "ts", "value").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 6).alias("back"), F.round(F.lead("value").over(w) - F.col("value"), 6).alias("ahead"))


@query("q_win_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 4) AS s FROM events")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return ev(spark, d, "event_id", "user_id", "ts", "value").select("event_id", F.round(F.sum("value").over(w), 4).alias("s"))


@query("q_win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(spark, d):
    e = ev(spark, d, "event_id", "user_id", "ts").withColumn("t", F.unix_timestamp(F.date_trunc("second", F.col("ts").cast("timestamp"))))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)).alias("n"))


@query("q_win_first_last", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS a, last_value(event_id) OVER w AS z FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, d):
    # one aggregate instead of a window and a distinct
    at = F.struct("ts", "event_id")
    return ev(spark, d, "event_id", "user_id", "ts").groupBy("user_id").agg(F.min(at)["event_id"].alias("a"), F.max(at)["event_id"].alias("z"))


@query("q_sort", "SELECT event_id, user_id FROM events ORDER BY user_id DESC NULLS LAST, event_id")
def _(spark, d):
    return ev(spark, d, "event_id", "user_id").orderBy(F.col("user_id").desc_nulls_last(), "event_id")


@query("q_topk", "SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 20")
def _(spark, d):
    return ev(spark, d, "event_id", "value").orderBy(F.desc("value"), "event_id").limit(20)


@query("q_topk_group", "SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS rn FROM events) WHERE rn <= 3")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return ev(spark, d, "user_id", "event_id", "value").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("user_id", "event_id")


@query("q_union", "SELECT user_id, 1.0::DOUBLE AS y FROM events WHERE event_type = 'click' UNION ALL SELECT user_id, 0.0::DOUBLE FROM events WHERE event_type = 'view'")
def _(spark, d):
    e = ev(spark, d, "user_id", "event_type")
    return e.where("event_type = 'click'").select("user_id", F.lit(1.0).alias("y")).unionByName(e.where("event_type = 'view'").select("user_id", F.lit(0.0).alias("y")))


for _name, _op, _sql in (("q_intersect", "intersect", "INTERSECT"), ("q_except", "subtract", "EXCEPT")):
    TABLE[_name] = ((lambda op: lambda spark, d: getattr(day_users(spark, d, 1), op)(day_users(spark, d, 2)))(_op), f"{DAY_SQL.format(1)} {_sql} {DAY_SQL.format(2)}")


@query("q_except_all", "SELECT l_suppkey FROM lineitem WHERE l_linenumber = 1 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_linenumber = 2")
def _(spark, d):
    x = li(spark, d, "l_suppkey", "l_linenumber")
    return x.where("l_linenumber = 1").select("l_suppkey").exceptAll(x.where("l_linenumber = 2").select("l_suppkey"))


@query("q_dedupe", "SELECT DISTINCT l_suppkey, l_partkey FROM lineitem")
def _(spark, d):
    return li(spark, d, "l_suppkey", "l_partkey").dropDuplicates()


def sql_pair(name: str, sql: str, names: tuple[str, ...]):
    """One text for both engines, over views of the tables."""

    def run(spark, d):
        text = sql
        for t in names:
            load_table(spark, d, t).createOrReplaceTempView(f"ft_{t}")
            text = text.replace(f" {t} ", f" ft_{t} ")
        return spark.sql(text)

    TABLE[name] = (run, sql)


sql_pair("q_subquery", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer ) AND c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000) AND EXISTS (SELECT 1 FROM nation WHERE n_nationkey = c_nationkey AND n_regionkey < 3)", ("customer", "orders", "nation"))
sql_pair("q_cte", "WITH c AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), m AS (SELECT max(n) AS top FROM c) SELECT o_custkey, n FROM c JOIN m ON n >= top - 3", ("orders",))


@query("q_str", "SELECT page_id, lower(regexp_extract(url, '^[a-z]+://([^/]+)', 1)) AS host, regexp_extract(url, '^[a-z]+://[^/]+/([^/?#]*)', 1) AS seg, concat_ws('-', substr(url, 1, 4), trim('  x ')) AS tag, regexp_replace(url, '[0-9]+', '#', 'g') AS shape, split_part(url, ':', 1) AS scheme FROM pages")
def _(spark, d):
    return load_table(spark, d, "pages", ["page_id", "url"]).select("page_id", F.lower(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).alias("host"), F.regexp_extract("url", "^[a-z]+://[^/]+/([^/?#]*)", 1).alias("seg"), F.concat_ws("-", F.substring("url", 1, 4), F.trim(F.lit("  x "))).alias("tag"), F.regexp_replace("url", "[0-9]+", "#").alias("shape"), F.split("url", ":")[0].alias("scheme"))


@query("q_words", "SELECT source, lang, count(*) AS n FROM (SELECT DISTINCT source, lang, unnest(regexp_extract_all(text, '[a-z]{6,}')) AS w FROM documents) GROUP BY ALL")
def _(spark, d):
    return load_table(spark, d, "documents", ["text", "source", "lang"]).select("source", "lang", F.explode(F.regexp_extract_all("text", F.lit("[a-z]{6,}"), F.lit(0))).alias("w")).distinct().groupBy("source", "lang").agg(F.count("*").alias("n"))


@query("q_date", "SELECT event_id, CAST(hour(ts) AS BIGINT) AS h, CAST(isodow(ts) AS BIGINT) AS dow, strftime(date_trunc('month', ts), '%Y-%m-%d') AS m, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS BIGINT) AS d, strftime(ts + INTERVAL 1 DAY, '%Y-%m-%d') AS nx FROM events")
def _(spark, d):
    return ev(spark, d, "event_id", "ts").select("event_id", long(F.hour("ts")).alias("h"), long(F.weekday("ts") + 1).alias("dow"), F.date_format(F.trunc("ts", "month"), "yyyy-MM-dd").alias("m"), long(F.datediff("ts", F.lit("2024-01-01").cast("date"))).alias("d"), F.date_format(F.date_add("ts", 1), "yyyy-MM-dd").alias("nx"))


@query("q_math", "SELECT event_id, round(exp(-value / 100), 9) AS e, round(ln(1 + value), 9) AS l, round(sqrt(value), 9) AS s, round(pow(value, 1.5), 4) AS p, sign(value - 50) AS g, greatest(value, 50) AS x, (user_id * 7 + 3) % 11 AS r FROM events WHERE value >= 0")
def _(spark, d):
    v = F.col("value")
    return ev(spark, d, "event_id", "value", "user_id").where("value >= 0").select("event_id", F.round(F.exp(-v / 100), 9).alias("e"), F.round(F.log1p(v), 9).alias("l"), F.round(F.sqrt(v), 9).alias("s"), F.round(F.pow(v, F.lit(1.5)), 4).alias("p"), F.signum(v - 50).cast("tinyint").alias("g"), F.greatest(v, F.lit(50.0)).alias("x"), F.pmod(F.col("user_id") * 7 + 3, F.lit(11)).alias("r"))


def phi_sql(x: str) -> str:
    """Φ in DuckDB for |x| <= 3 by its positive series."""
    return f"(0.5 + sign({x}) * exp(-0.5 * ({x}) * ({x})) / sqrt(2 * pi()) * list_sum(list_transform(range(60), lambda n: exp(n * ln(2.0) + lgamma(n + 1.0) - lgamma(2.0 * n + 2.0) + (2.0 * n + 1.0) * ln(greatest(abs({x}), 1e-12))))))"


@query("q_phi", f"SELECT i, n, round({phi_sql('x')}, 9) AS phi, round(ln({phi_sql('x')}), 8) AS log_phi, round(exp(-0.5 * x * x) / sqrt(2 * pi()) / {phi_sql('x')}, 8) AS haz FROM (SELECT i, n, (i - 28) / 10.0 AS x FROM (SELECT user_id % 57 AS i, count(*) AS n FROM events GROUP BY i))")
def _(spark, d):
    from ..functions.special import hazard_expr, log_ndtr_expr, ndtr_expr

    x = (F.col("i") - 28) / 10.0
    scores = ev(spark, d, "user_id").groupBy((F.col("user_id") % 57).alias("i")).agg(F.count("*").alias("n"))  # these expressions are long: each value once
    return scores.select("i", "n", F.round(ndtr_expr(x), 9).alias("phi"), F.round(log_ndtr_expr(x), 8).alias("log_phi"), F.round(hazard_expr(x), 8).alias("haz"))


@query("q_array", "SELECT vec_id, round(list_sum(list_transform(list_zip(embedding[1:8], embedding[9:16]), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 6) AS dot, len(list_filter(embedding, lambda v: v > 0)) AS pos FROM embeddings")
def _(spark, d):
    e = F.col("embedding")
    dot = F.aggregate(F.zip_with(F.slice(e, 1, 8), F.slice(e, 9, 8), lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return load_table(spark, d, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.round(dot, 6).alias("dot"), long(F.size(F.filter(e, lambda v: v > 0))).alias("pos"))


@query("q_map", "SELECT event_id, name, v FROM (SELECT event_id, unnest(['length', 'amp2', 'beta']) AS name, unnest([value / 2, value, (user_id % 4) / 2]::DOUBLE[]) AS v FROM events)")
def _(spark, d):
    m = F.map_from_arrays(F.array(*map(F.lit, ("length", "amp2", "beta"))), F.array(F.col("value") / 2, F.col("value"), F.col("user_id") % 4 / 2))
    return ev(spark, d, "event_id", "user_id", "value").select("event_id", F.explode(F.map_entries(m)).alias("e")).select("event_id", F.col("e.key").alias("name"), F.col("e.value").alias("v"))


@query("q_struct", f"SELECT user_id, {K_SQL} AS k, value FROM events WHERE event_type = 'click'")
def _(spark, d):
    e = ev(spark, d, "user_id", "props", "value", "event_type").where("event_type = 'click'")
    return e.select(F.array(F.struct(F.struct("user_id", K().alias("k")).alias("at"), "value")).alias("cells")).select(F.inline("cells")).select("at.user_id", "at.k", "value")


@query("q_explode", "SELECT item_id, CAST(pos - 1 AS BIGINT) AS pos, ws[pos] AS word FROM (SELECT item_id, string_split(text, ' ') AS ws, unnest(range(1, len(string_split(text, ' ')) + 1)) AS pos FROM benchmark)")
def _(spark, d):
    return load_table(spark, d, "benchmark", ["item_id", "text"]).select("item_id", F.posexplode(F.split("text", " ")).alias("pos", "word")).select("item_id", long(F.col("pos")).alias("pos"), "word")


@query("q_json", f"SELECT event_id, {K_SQL} AS k, '{{\"k\":' || {K_SQL} || '}}' AS j FROM events")
def _(spark, d):
    s = F.from_json("props", "k bigint")
    return ev(spark, d, "event_id", "props").select("event_id", s["k"].alias("k"), F.to_json(F.struct(s["k"].alias("k"))).alias("j"))


@query("q_cast", "SELECT page_id, TRY_CAST(regexp_extract(url, '/([0-9]+)', 1) AS INTEGER) AS n, CAST(CAST(page_id AS DECIMAL(12, 2)) / 4 AS DOUBLE) AS q, CAST(page_id AS VARCHAR) AS s FROM pages")
def _(spark, d):
    return load_table(spark, d, "pages", ["page_id", "url"]).select("page_id", F.regexp_extract("url", "/([0-9]+)", 1).try_cast("int").alias("n"), (F.col("page_id").cast("decimal(12,2)") / 4).cast("double").alias("q"), F.col("page_id").cast("string").alias("s"))


@query("q_udf_scalar", f"SELECT i, round({phi_sql('x')}, 9) AS phi FROM (SELECT event_id AS i, (user_id % 57 - 28) / 10.0 AS x FROM events)")
def _(spark, d):
    from ..functions.special import ndtr
    from ..session import ship_package

    ship_package(spark)

    @F.pandas_udf("double")
    def ndtr_udf(x: pd.Series) -> pd.Series:
        return pd.Series(ndtr(x.to_numpy()))

    return ev(spark, d, "event_id", "user_id").select(F.col("event_id").alias("i"), F.round(ndtr_udf((F.col("user_id") % 57 - 28) / 10.0), 9).alias("phi"))


@query("q_udf_grouped", "SELECT l_suppkey, round(sum(l_quantity * l_extendedprice) / sum(l_quantity * l_quantity), 6) AS w FROM lineitem GROUP BY l_suppkey")
def _(spark, d):
    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y = pdf["l_quantity"].to_numpy(), pdf["l_extendedprice"].to_numpy()
        return pd.DataFrame({"l_suppkey": [int(pdf["l_suppkey"].iloc[0])], "w": [float(x @ y / (x @ x))]})

    return li(spark, d, "l_suppkey", "l_quantity", "l_extendedprice").groupBy("l_suppkey").applyInPandas(solve, "l_suppkey long, w double").select("l_suppkey", F.round("w", 6).alias("w"))


@query("q_udf_cogroup", "SELECT a.u AS user_id, a.n AS train, coalesce(b.n, 0) AS test FROM (SELECT user_id AS u, count(*) AS n FROM events WHERE CAST(ts AS DATE) = DATE '2024-01-01' GROUP BY 1) a LEFT JOIN (SELECT user_id AS u, count(*) AS n FROM events WHERE CAST(ts AS DATE) = DATE '2024-01-02' GROUP BY 1) b ON a.u = b.u")
def _(spark, d):
    e = ev(spark, d, "user_id", "ts")
    day = lambda n: e.where(F.to_date("ts") == F.lit(f"2024-01-0{n}").cast("date")).select("user_id")

    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": a["user_id"].iloc[:1], "train": [len(a)] if len(a) else [], "test": [len(b)] if len(a) else []})

    return day(1).groupBy("user_id").cogroup(day(2).groupBy("user_id")).applyInPandas(both, "user_id long, train long, test long")


@query("q_udaf_vecsum", "SELECT round(sum(embedding[1]::DOUBLE), 4) AS a, round(sum(embedding[2]::DOUBLE), 4) AS b FROM embeddings")
def _(spark, d):
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    v = array_to_vector(F.transform(F.slice("embedding", 1, 2), lambda x: x.cast("double")))
    s = load_table(spark, d, "embeddings", ["embedding"]).select(v.alias("v")).select(Summarizer.sum(F.col("v")).alias("s")).select(vector_to_array("s").alias("s"))
    return s.select(F.round(F.col("s")[0], 4).alias("a"), F.round(F.col("s")[1], 4).alias("b"))


@query("q_udtf_zeros", "SELECT n_nationkey, a, ((n_nationkey * 7 + a * 13) % 25)::BIGINT AS i_1 FROM nation, range(3) t(a)")
def _(spark, d):
    @F.udtf(returnType="a bigint, i_1 bigint")
    class ZeroCandidates:
        def eval(self, key: int, attempts: int):
            for a in range(attempts):
                yield a, (key * 7 + a * 13) % 25

    spark.udtf.register("zero_candidates", ZeroCandidates)
    load_table(spark, d, "nation").createOrReplaceTempView("ft_nation")
    return spark.sql("SELECT n_nationkey, z.a, z.i_1 FROM ft_nation, LATERAL zero_candidates(n_nationkey, 3) z")


@query("q_sql_surface", f"SELECT i, round({phi_sql('x')}, 9) AS phi FROM (SELECT event_id AS i, (user_id % 57 - 28) / 10.0 AS x FROM events) WHERE i % 2 = 0")
def _(spark, d):
    from ..functions.special import ndtr
    from ..session import ship_package

    ship_package(spark)

    @F.pandas_udf("double")
    def f(x: pd.Series) -> pd.Series:
        return pd.Series(ndtr(x.to_numpy()))

    spark.udf.register("ndtr", f)
    ev(spark, d, "event_id", "user_id").createOrReplaceTempView("ft_events")
    return spark.sql("SELECT event_id AS i, round(ndtr((user_id % 57 - 28) / 10.0D), 9) AS phi FROM ft_events WHERE event_id % 2 = 0")


@query("q_sample", f"SELECT event_id FROM events WHERE {portable_hash_sql('event_id', seed=4)} < {MODULUS // 10}")
def _(spark, d):
    """A tenth by hash: the same rows in every layout."""
    return ev(spark, d, "event_id").where(portable_hash(F.col("event_id"), seed=4) < MODULUS // 10)


@query("q_skew", "SELECT event_type, count(*) AS n, round(sum(value), 3) AS s FROM events GROUP BY event_type")
def _(spark, d):
    """A hot key counted in two levels: salted partial sums, then their sum."""
    part = ev(spark, d, "event_id", "event_type", "value").groupBy("event_type", F.pmod(F.xxhash64("event_id"), F.lit(16)).alias("salt")).agg(F.count("*").alias("n"), F.sum("value").alias("s"))
    return part.groupBy("event_type").agg(F.sum("n").alias("n"), F.round(F.sum("s"), 3).alias("s"))


@query("q_explain", "SELECT check_name, true AS holds FROM (VALUES ('filter pushed'), ('columns pruned'), ('one code-generated stage'), ('key-free has no keyed exchange'), ('keyed has one')) t(check_name)")
def _(spark, d):
    """What the plans must show, read from the plans."""
    from ..bounds import gaussian
    from ..exec import passes
    from .tensor_queries import folded, sine_model

    plan = lambda df: df._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    scan = plan(li(spark, d, "l_orderkey", "l_quantity").where("l_quantity > 45"))
    t, m = folded(spark, d).distribute(2), sine_model()
    a = gaussian.adjoints(m, passes.suff_stats(t, m))[0]
    keyed = plan(passes.keyed_gradient(t, m, a))
    free = plan(t.df.select(*t.modes, "y").mapInArrow(lambda batches: iter(()), "v binary"))
    t.release()
    rows = [
        ("filter pushed", "GreaterThan(l_quantity,45" in scan),
        ("columns pruned", "ReadSchema: struct<l_orderkey:bigint,l_quantity:double>" in scan),
        ("one code-generated stage", "[codegen id : 1]" in scan and "[codegen id : 2]" not in scan),
        ("key-free has no keyed exchange", "hashpartitioning" not in free.split("InMemoryRelation")[0]),
        ("keyed has one", "hashpartitioning(mode" in keyed),
    ]
    return spark.createDataFrame(rows, "check_name string, holds boolean")


_ZERO_INDEX = ", ".join(f"({portable_hash_sql('j', str(k + 1))} // 256) % {n} AS i_{k + 1}" for k, n in enumerate((100, 50, 25)))


_CLICK_CELLS = f"SELECT DISTINCT user_id % 100 AS i_1, CAST(hour(ts) AS BIGINT) AS i_2, {K_SQL} % 25 AS i_3 FROM events WHERE event_type = 'click'"


@query("q_datasource", f"WITH c AS ({_CLICK_CELLS}) SELECT i_1, i_2, i_3 FROM (SELECT {_ZERO_INDEX} FROM (SELECT unnest(range((SELECT count(*) FROM c))) AS j)) ANTI JOIN c USING (i_1, i_2, i_3)")
def _(spark, d):
    """Candidates from the reader, as many as there are cells with clicks, without those cells."""
    from ..sources.tables import register_tensor_zeros

    register_tensor_zeros(spark)
    e = ev(spark, d, "user_id", "ts", "props", "event_type").where("event_type = 'click'")
    cells = e.select((F.col("user_id") % 100).alias("i_1"), long(F.hour("ts")).alias("i_2"), (K() % 25).alias("i_3")).distinct()
    drawn = spark.read.format("tensor_zeros").options(dims="100,50,25", n=str(cells.count()), parts="4").load()
    return drawn.join(cells, ["i_1", "i_2", "i_3"], "left_anti")
