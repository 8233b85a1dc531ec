"""Queries of aggregates, windows and dates around the products, and of streams."""

from __future__ import annotations

import functools

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..plans import cost
from ..plans.work import number_rows, prefix_sum, row_work
from ..sources import builders as src
from ..streaming import increments as inc
from .matrices import query as _query

QUERIES, ORACLES = {}, {}
query = functools.partial(_query, into=(QUERIES, ORACLES))
PF = src.part_follow


@query("select count(*) as rows, cast(sum(n) as bigint) nnz, max(n) max_n, quantile_cont(n, 0.5) median_n, round(stddev_pop(n), 6) sd_n, round((avg(n * n * n) - 3 * avg(n) * avg(n * n) + 2 * power(avg(n), 3)) / power(stddev_pop(n), 3), 6) skew_n from (select i, count(*) n from pf group by 1)")
def row_profile(s, d):
    return cost.row_profile(PF(s, d)).withColumn("skew_n", F.round("skew_n", 6))


@query("select i, j, v from (select *, row_number() over (partition by i order by v desc, j) r from pf) where r = 1")
def heaviest_column(s, d):
    return PF(s, d).df.groupBy("i").agg(F.max_by(F.struct("j", "v"), F.struct("v", -F.col("j"))).alias("m")).select("i", "m.j", "m.v")


@query("select user_id, " + ", ".join(f"count(*) filter (event_type = '{t}') as {t}" for t in src.EVENT_TYPES) + " from events group by 1")
def pivot_user_type(s, d):
    e = src.table(s, d, "events").groupBy("user_id").pivot("event_type", list(src.EVENT_TYPES)).agg(F.count(F.lit(1)))
    return e.na.fill(0)


@query("select user_id, event_type, count(*) n from events where event_type in ('click', 'view') group by 1, 2")
def unpivot_user_type(s, d):
    e = src.table(s, d, "events").where("event_type in ('click', 'view')").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return e.unpivot("user_id", ["click", "view"], "event_type", "n").where("n is not null")


_FLAGS = "fl as (select l_returnflag f, l_linestatus s, count(*) n, cast(sum(cast(l_quantity as bigint)) as bigint) q from lineitem group by 1, 2)"
for _name, _sql in (("rollup", "rollup (f, s)"), ("cube", "cube (f, s)"), ("grouping_sets", "grouping sets ((f), (s))")):
    def _grouped(s, d, name):
        x = src.table(s, d, "lineitem").select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"), F.col("l_quantity").cast("bigint").alias("q"))
        if name == "grouping_sets":
            x.createOrReplaceTempView("flagged_lines")
            return s.sql("select f, s, count(*) n, sum(q) q from flagged_lines group by grouping sets ((f), (s))")
        return getattr(x, name)("f", "s").agg(F.count("*").alias("n"), F.sum("q").alias("q"))

    query(f"select f, s, cast(sum(n) as bigint) n, cast(sum(q) as bigint) q from fl group by {_sql}", _FLAGS, name=f"work_{_name}")(functools.partial(_grouped, name=_name))


@query("select i, work, rank() over (order by work desc) rk, dense_rank() over (order by work desc) dr from (select x.i, cast(sum(n) as bigint) work from sf x join (select i, count(*) n from sf group by 1) y on x.j = y.i group by 1)")
def rank_rows(s, d):
    m = src.supplier_follow(s, d)
    rows = row_work(m, m, all_rows=False).where("work > 0").select("i", "work")
    # Ranks belong to the different works: a running count over these, not one task's window over all rows.
    ranks = prefix_sum(rows.groupBy("work").agg(F.count("*").alias("n")).withColumn("down", -F.col("work")), ["down"], "n", "more")
    ranks = number_rows(ranks, ["down"], "place")
    return rows.join(ranks.select("work", "more", "place"), "work").select("i", "work", (F.col("more") + 1).alias("rk"), (F.col("place") + 1).alias("dr"))


@query("select i, j, v, round(percent_rank() over w, 6) pr, round(cume_dist() over w, 6) cd, ntile(4) over w nt, first_value(j) over w f, last_value(j) over (partition by i order by v, j rows between unbounded preceding and unbounded following) l, nth_value(j, 2) over (partition by i order by v, j rows between unbounded preceding and unbounded following) n2, lag(j) over w pj, lead(j) over w nj from pf window w as (partition by i order by v, j)")
def window_analytics(s, d):
    w = W.partitionBy("i").orderBy("v", "j")
    a = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return PF(s, d).df.select("i", "j", "v", F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(w).cast("bigint").alias("nt"), F.first("j").over(w).alias("f"), F.last("j").over(a).alias("l"),
                              F.nth_value("j", 2).over(a).alias("n2"), F.lag("j").over(w).alias("pj"), F.lead("j").over(w).alias("nj"))


@query("select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) n from events")
def events_range_frame(s, d):
    e = src.table(s, d, "events")
    w = W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


@query("select cast(date_trunc('month', o_orderdate) as date) as month_start, count(*) n, max(date_diff('day', o_orderdate, l_shipdate)) most_days from orders join lineitem on l_orderkey = o_orderkey group by 1")
def date_functions(s, d):
    o, x = src.table(s, d, "orders"), src.table(s, d, "lineitem").select("l_orderkey", "l_shipdate")
    j = o.join(x, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy(F.trunc(F.col("o_orderdate").cast("date"), "month").alias("month_start")).agg(F.count("*").alias("n"), F.max(F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date"))).cast("bigint").alias("most_days"))


@query("select page_id, lower(regexp_extract(url, 'https?://([^/?#]*)', 1)) as host, length(url) n from pages")
def url_functions(s, d):
    return src.table(s, d, "pages").select("page_id", F.lower(F.regexp_extract("url", "https?://([^/?#]*)", 1)).alias("host"), F.length("url").cast("bigint").alias("n"))


# Streams: each must equal the batch aggregate over the same rows

@query("select user_id i, k.j, cast(count(*) as bigint) v from events join ety on event_type = name join kb k on k.i = id group by 1, 2", "kb as (select * from (values (0, 0), (0, 1), (1, 1), (2, 0), (3, 2), (4, 2)) t(i, j))")
def stream_increment(s, d):
    from ..matrix import SparseMatrix

    b = SparseMatrix(s.createDataFrame([(0, 0, 1), (0, 1, 1), (1, 1, 1), (2, 0, 1), (3, 2, 1), (4, 2, 1)], "i bigint, j bigint, v bigint"), 5, 3)
    e = inc.event_stream(s, d).select(F.col("user_id").alias("i"), src.event_type_id().alias("j"), F.lit(1).cast("bigint").alias("v")).where("j is not null")
    return inc.drain(inc.product_increment(e, b), "complete").select("i", F.col("j").cast("int").alias("j"), "v")


@query("select cast(time_bucket(interval 1 day, ts, timestamp '1970-01-01') as timestamp) as start, user_id, event_type, count(*) n from events group by 1, 2, 3")
def stream_tumbling(s, d):
    return inc.drain(inc.tumbling(inc.event_stream(s, d)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select cast(b - o as timestamp) as start, event_type, count(*) n from (select *, time_bucket(interval 12 hours, ts, timestamp '1970-01-01') b from events) cross join (select unnest([interval 0 hours, interval 12 hours]) o) group by 1, 2")
def stream_sliding(s, d):
    return inc.drain(inc.sliding(inc.event_stream(s, d)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select user_id, min(ts) as start, max(ts) + interval 1 hour as \"end\", count(*) n from (select *, sum(new) over (partition by user_id order by ts, event_id) g from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 1 hour then 0 else 1 end new from events)) group by user_id, g")
def stream_session(s, d):
    out = inc.drain(inc.sessions(inc.event_stream(s, d)), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "n")


@query("select user_id, event_type, count(*) n from (select distinct user_id, event_type from events) group by 1, 2")
def stream_dedup_edges(s, d):
    e = inc.dedup_edges(inc.event_stream(s, d), ["user_id", "event_type"], "4000 days")
    return inc.drain(e.select("user_id", "event_type"), "append").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


@query("select user_id i, count(*) n, cast(sum(id) as bigint) total from events join ety on event_type = name group by 1")
def stream_state_rows(s, d):
    e = inc.event_stream(s, d).select(F.col("user_id").alias("i"), src.event_type_id().alias("v")).where("v is not null")
    return inc.drain(inc.stateful_rows(e), "update").groupBy("i").agg(F.max_by(F.struct("n", "total"), "n").alias("x")).select("i", "x.n", "x.total")


@query("select event_type, count(*) n from events group by 1")
def stream_late(s, d):
    """Nothing is late within one drain: a watermark drops rows only against earlier batches."""
    e = inc.event_stream(s, d).withWatermark("ts", "10 minutes")
    w = e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return inc.drain(w.select("event_type", "n"), "complete").groupBy("event_type").agg(F.sum("n").alias("n"))


