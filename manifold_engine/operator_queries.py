"""Relational, streaming and SQL-surface operators in the roles the methods need them for."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import queries as core
from . import sql_surface
from .functions import metrics as D
from .operators import landmarks as L
from .operators import maps as M
from .operators import pairs as P
from .queries import DEG_SQL, LM_SQL, NEAR, P_SQL, PLANE_SQL, PR_SQL, plane_cells, plane_model, r6, user_cells, user_pairs, user_tree, users
from .sources import points as R
from .spool import spool
from .streaming import embed as X

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return add


DAY = "(epoch_us(ts) % 86400000000)"


@query(f"select event_id as id, round(value / 100.0, 6) + 0.0 as x, round(3.0 * ({DAY} / 86400000000.0), 6) + 0.0 as y from events where value between 5.0 and 250.0 and event_type in ('click', 'view', 'purchase', 'error', 'signup') and value is not null")
def op_scan_project_filter(s, d):
    """Pruned scan, pushed range and membership predicates, projection to features."""
    e = R.table(s, d, "events").where(F.col("value").between(5.0, 250.0) & F.col("event_type").isin("click", "view", "purchase", "error", "signup") & F.col("value").isNotNull())
    return e.select(F.col("event_id").alias("id"), r6(F.col("value") / 100.0).alias("x"), r6(F.lit(3.0) * R.day_fraction(F.col("ts"))).alias("y"))


@query("with q as (select l_orderkey, sum(l_quantity) as q from lineitem group by l_orderkey) select o_orderkey as id, round(o_totalprice / 5e5, 9) + 0.0 as a, round((coalesce(c_acctbal, 0.0) + 1000.0) / 11000.0, 9) + 0.0 as c, round(least(coalesce(q, 0.0) / 300.0, 1.0), 9) + 0.0 as d from orders left join customer on o_custkey = c_custkey left join q on o_orderkey = l_orderkey")
def op_feature_join_agg(s, d):
    """Latents of the chains: inner sums, left joins with defaults."""
    q = R.table(s, d, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"))
    o = R.table(s, d, "orders").join(R.table(s, d, "customer").select("c_custkey", "c_acctbal"), F.col("o_custkey") == F.col("c_custkey"), "left").join(q, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    return o.select(F.col("o_orderkey").alias("id"), r6(F.col("o_totalprice") / 5e5, 9).alias("a"), r6((F.coalesce("c_acctbal", F.lit(0.0)) + 1000.0) / 11000.0, 9).alias("c"), r6(F.least(F.coalesce("q", F.lit(0.0)) / 300.0, F.lit(1.0)), 9).alias("d"))


@query("select o_orderkey as id, ntile(5) over (order by md5('0:' || o_orderkey), o_orderkey) as fold from orders")
def op_fold_ntile(s, d):
    return R.folds(R.table(s, d, "orders").select(F.col("o_orderkey").alias("id"))).withColumn("fold", F.col("fold").cast("long"))


@query(f"with {LM_SQL} select id, lid, round(d, 6) + 0.0 as d from v")
def op_broadcast_assign(s, d):
    """Nearest landmark by a broadcast nested-loop join and ``min_by`` (the landmark side is a parameter-bound sample)."""
    p, ids, z, _ = user_cells(s, d)
    lm = s.createDataFrame(pa.table({"lid": pa.array(ids), "z": pa.array(list(z), pa.list_(pa.float64()))}))
    q = p.crossJoin(F.broadcast(lm)).select("id", "lid", D.euclidean(F.col("vec"), F.col("z")).alias("d"))
    return q.groupBy("id").agg(F.min(F.struct("d", "lid")).alias("m")).select("id", "m.lid", r6(F.col("m.d")).alias("d"))


@query(core.WITHIN_SQL)
def op_grid_range_join(s, d):
    return P.grid_pairs(users(s, d), NEAR, 2).select("i", "j", r6(F.col("d")).alias("d"))


@query(core.WITHIN_SQL)
def op_theta_join(s, d):
    return P.theta_pairs(users(s, d), D.euclidean, NEAR).select("i", "j", r6(F.col("d")).alias("d"))


@query("select a.event_id as i, b.event_id as j, a.user_id from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts < a.ts + interval 1 hour")
def op_band_join(s, d):
    """Events of a user less than an hour apart: the hour is a join key, the next hour the only other candidate."""
    e = R.table(s, d, "events").select("event_id", "user_id", "ts", (F.unix_date(F.col("ts").cast("date")) * 24 + F.hour("ts")).alias("h"))
    a = e.select(F.col("event_id").alias("i"), "user_id", F.col("ts").alias("t0"), F.explode(F.array(F.col("h"), F.col("h") + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("j"), "user_id", F.col("ts").alias("t1"), "h")
    return a.join(b, ["user_id", "h"]).where((F.col("t1") > F.col("t0")) & (F.col("t1") < F.col("t0") + F.expr("interval 1 hour"))).select("i", "j", "user_id")


@query("select p.event_id as id, (select max(e.event_id) from events e where e.user_id = p.user_id and e.event_type = 'error' and (e.ts, e.event_id) < (p.ts, p.event_id)) as error_id from events p where p.event_type = 'purchase'")
def op_asof_join(s, d):
    """Last error of the user before each purchase: one window, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = R.table(s, d, "events")
    return e.withColumn("error_id", F.last(F.when(F.col("event_type") == "error", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select(F.col("event_id").alias("id"), "error_id")


COVER = f"{PR_SQL}, lm as (select id as lid from p order by md5('0:' || id), id limit 15), c as (select distinct i as id from (select i, j from pr where d <= {NEAR} union all select j, i from pr where d <= {NEAR} union all select id, id from p) where j in (select lid from lm))"


def covered(s, d):
    """Users, and those within reach of a landmark: every user is measured against the landmarks, no pair of users is."""
    p = users(s, d)
    ids, z = L.vectors_of(p, L.random_landmarks(p, 15))
    return p, M.assign(p, ids, z).where(F.col("d") <= NEAR).select("id")


@query(f"with {COVER} select id from p where id in (select id from c)")
def op_semi_cover(s, d):
    p, c = covered(s, d)
    return p.join(c, "id", "left_semi").select("id")


@query(f"with {COVER} select id from p where id not in (select id from c)")
def op_anti_cover(s, d):
    p, c = covered(s, d)
    return p.join(c, "id", "left_anti").select("id")


MED = f"{LM_SQL}, o as (select i, j, d from pr union all select j, i, d from pr union all select id, id, 0.0 from p), cc as (select a.lid, a.id, sum(o.d) as cost from v a join v b on a.lid = b.lid join o on o.i = a.id and o.j = b.id group by a.lid, a.id), md as (select arg_min(id, (round(cost, 9), id)) as medoid from cc group by lid)"


@query(f"with {MED} select coalesce(lid, medoid) as id, lid is not null as before, medoid is not null as after from (select lid from lm) full outer join (select distinct medoid from md) on lid = medoid")
def op_full_outer_medoids(s, d):
    """Landmarks entering and leaving in one medoid round."""
    p, ids, _, cells = user_cells(s, d)
    old = s.createDataFrame(pa.table({"lid": pa.array(ids)}))
    new = L.medoid_update(p, cells).select("medoid").distinct()
    return old.join(new, F.col("lid") == F.col("medoid"), "full_outer").select(F.coalesce("lid", "medoid").alias("id"), F.col("lid").isNotNull().alias("before"), F.col("medoid").isNotNull().alias("after"))


@query(f"with {PLANE_SQL} select id, lid, round(d, 6) + 0.0 as d from v order by v.d desc, id limit 10")
def op_topk_worst(s, d):
    p, ids, z = plane_cells(s, d)
    return M.assign(p, ids, z).orderBy(F.desc("d"), "id").limit(10).select("id", "lid", r6(F.col("d")).alias("d"))


@query(f"with {PR_SQL}, o as (select i as id, j as nn, d from pr union all select j, i, d from pr), r as (select id, nn, row_number() over (partition by id order by d, nn) as rn, rank() over (partition by id order by floor(d * 4)) as rk, dense_rank() over (partition by id order by floor(d * 4)) as dr from o) select * from r where rn <= 5")
def op_knn_rank(s, d):
    """Ranks of the five nearest: a point of a smaller whole part of ``4 d`` is also a nearer one, so their ranks among all are those among the five."""
    p = users(s, d)
    w, b = Window.partitionBy("id"), F.floor(F.col("d") * 4)
    o = P.knn(p, p, 5).select("id", "nn", F.row_number().over(w.orderBy("d", "nn")).alias("rn"), F.rank().over(w.orderBy(b)).alias("rk"), F.dense_rank().over(w.orderBy(b)).alias("dr")).where("rn <= 5")
    return o.select("id", "nn", *[F.col(c).cast("long").alias(c) for c in ("rn", "rk", "dr")])


@query("with e as (select event_id as id, value, lag(value) over w as b, lead(event_id) over w as nxt from events window w as (partition by user_id order by ts, event_id)) select id, round(abs(value - b), 6) + 0.0 as step, nxt from e")
def op_lag_steps(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return R.table(s, d, "events").select(F.col("event_id").alias("id"), r6(F.abs(F.col("value") - F.lag("value").over(w))).alias("step"), F.lead("event_id").over(w).alias("nxt"))


@query(f"with {core.H_SQL} select id, cast(b as int) as b, round(s, 6) + 0.0 as cdf from cdf")
def op_running_cdf(s, d):
    h = R.histograms(s, d).select("id", F.posexplode("vec").alias("b", "w"))
    return h.select("id", "b", r6(F.sum("w").over(Window.partitionBy("id").orderBy("b").rowsBetween(Window.unboundedPreceding, 0))).alias("cdf"))


@query("select event_id as id, round(avg(value) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row), 6) + 0.0 as mean from events")
def op_range_frame(s, d):
    t = F.unix_date(F.col("ts").cast("date")).cast("long") * 86_400_000_000 + R.day_micros(F.col("ts"))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-3_600_000_000, 0)
    return R.table(s, d, "events").withColumn("t", t).select(F.col("event_id").alias("id"), r6(F.avg("value").over(w)).alias("mean"))


GS = "select o_orderstatus as status, o_orderpriority as priority, count(*) as n, round(avg(o_totalprice), 2) + 0.0 as mean from orders group by "


def _cover_table(s, d):
    return R.table(s, d, "orders").select(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), "o_totalprice")


def _counts(g):
    return g.agg(F.count("*").alias("n"), r6(F.avg("o_totalprice"), 2).alias("mean"))


@query(GS + "rollup (o_orderstatus, o_orderpriority)")
def op_rollup_cover(s, d):
    return _counts(_cover_table(s, d).rollup("status", "priority"))


@query(GS + "cube (o_orderstatus, o_orderpriority)")
def op_cube_cover(s, d):
    return _counts(_cover_table(s, d).cube("status", "priority"))


@query(GS + "grouping sets ((o_orderstatus), (o_orderpriority), ())")
def op_grouping_sets_cover(s, d):
    return _counts(_cover_table(s, d).groupingSets([("status",), ("priority",), ()], "status", "priority"))


TYPES = ["click", "error", "purchase", "signup", "view"]


@query(f"with {PLANE_SQL} select v.lid, " + ", ".join(f"count(*) filter (where event_type = '{t}') as {t}" for t in TYPES) + " from v join events on event_id = id group by v.lid")
def op_pivot_cells(s, d):
    p, ids, z = plane_cells(s, d)
    e = R.table(s, d, "events").select(F.col("event_id").alias("id"), "event_type")
    out = M.assign(p, ids, z).join(e, "id").groupBy("lid").pivot("event_type", TYPES).agg(F.count(F.lit(1)))
    return out.select("lid", *[F.coalesce(t, F.lit(0)).cast("long").alias(t) for t in TYPES])


@query("select event_type, count(distinct user_id) as users from events group by event_type")
def op_distinct_exact(s, d):
    return R.table(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query()
def op_distinct_approx(s, d):
    return R.table(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


@query(f"with {PR_SQL} select round(quantile_cont(d, 0.25), 6) + 0.0 as q25, round(quantile_cont(d, 0.5), 6) + 0.0 as q50, round(quantile_cont(d, 0.75), 6) + 0.0 as q75 from pr")
def op_quantiles(s, d):
    return user_pairs(s, d)[1].agg(*[r6(F.percentile("d", q)).alias(n) for n, q in (("q25", 0.25), ("q50", 0.5), ("q75", 0.75))])


@query()
def op_quantile_sketch(s, d):
    """Distance quantiles by a mergeable sketch, for a bandwidth over pair tables of any size."""
    return P.all_pairs(users(s, d)).agg(F.percentile_approx("d", [0.25, 0.5, 0.75], 1000).alias("q"))


def two_selections(s, d):
    p = users(s, d)
    return p, L.random_landmarks(p, 30, 0), L.random_landmarks(p, 30, 1)


SEL = f"{P_SQL}, a as (select id as lid from p order by md5('0:' || id), id limit 30), b as (select id as lid from p order by md5('1:' || id), id limit 30)"


@query(f"with {SEL} select lid from a union all select lid from b")
def op_union_new(s, d):
    _, a, b = two_selections(s, d)
    return a.unionByName(b)


@query(f"with {SEL} select lid from a intersect select lid from b")
def op_intersect_sel(s, d):
    _, a, b = two_selections(s, d)
    return a.intersect(b)


@query(f"with {SEL} select lid from a except all select lid from b")
def op_except_sel(s, d):
    _, a, b = two_selections(s, d)
    return a.exceptAll(b)


@query("with x as (select vec_id as id, list_transform(embedding, lambda e: cast(e as double)) as v from embeddings) select id, round(sqrt(list_sum(list_transform(v, lambda e: e * e))), 6) + 0.0 as norm, round(list_avg(v), 6) + 0.0 as mean, round(list_sum(list_transform(list_zip(v[1:32], v[33:64]), lambda t: t[1] * t[2])), 6) + 0.0 as halves from x")
def op_array_math(s, d):
    def total(c):
        return F.aggregate(c, F.lit(0.0), lambda a, x: a + x)

    v = F.col("vec")
    return R.vectors(s, d).select("id", r6(F.sqrt(total(F.transform(v, lambda x: x * x)))).alias("norm"), r6(total(v) / F.size(v)).alias("mean"), r6(total(F.zip_with(F.slice(v, 1, 32), F.slice(v, 33, 32), lambda x, y: x * y))).alias("halves"))


@query("select event_id as id, cast(json_extract_string(props, '$.k') as bigint) as k, case when event_type = 'error' then 1.0 :: double else 0.0 :: double end as error, value as value from events")
def op_map_json(s, d):
    """JSON and map features flattened over a stated key list."""
    e = R.table(s, d, "events").select(F.col("event_id").alias("id"), F.get_json_object("props", "$.k").cast("long").alias("k"), F.map_from_entries(F.array(F.struct(F.lit("value").alias("k"), F.col("value").alias("v")), F.struct(F.concat(F.lit("is_"), "event_type").alias("k"), F.lit(1.0).alias("v")))).alias("m"))
    return e.select("id", "k", F.coalesce(F.try_element_at("m", F.lit("is_error")), F.lit(0.0)).alias("error"), F.try_element_at("m", F.lit("value")).alias("value"))


@query(f"with {core.CODE_SQL} select id, code from k")
def op_string_shingles(s, d):
    return R.codes(s, d).select("id", "code")


@query(f"select event_id as id, cast(extract(hour from ts) as bigint) as hour, round(sin(2.0 * pi() * {DAY} / 86400000000.0), 6) + 0.0 as s, round(cos(2.0 * pi() * {DAY} / 86400000000.0), 6) + 0.0 as c, cast(datediff('day', date '2020-01-01', cast(ts as date)) as bigint) as day from events")
def op_date_cycle(s, d):
    a = F.lit(2.0 * math.pi) * R.day_micros(F.col("ts")) / F.lit(86_400_000_000.0)
    return R.table(s, d, "events").select(F.col("event_id").alias("id"), F.hour("ts").cast("long").alias("hour"), r6(F.sin(a)).alias("s"), r6(F.cos(a)).alias("c"), F.date_diff(F.col("ts").cast("date"), F.lit("2020-01-01").cast("date")).cast("long").alias("day"))


@query("with z as (select o_orderkey, o_custkey, floor(o_totalprice / 50000.0) as cell from orders) select cast(cell as bigint) as cell, coalesce(r_name, 'none') as region, count(*) as n from z left join customer on o_custkey = c_custkey left join nation on c_nationkey = n_nationkey left join region on n_regionkey = r_regionkey group by 1, 2")
def op_colour_join(s, d):
    """Composition of cells of the roll's angle by region, over dimension joins."""
    t = lambda n: R.table(s, d, n)
    z = t("orders").select("o_custkey", F.floor(F.col("o_totalprice") / 50000.0).alias("cell"))
    z = z.join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"), "left").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey"), "left").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"), "left")
    return z.groupBy("cell", F.coalesce("r_name", F.lit("none")).alias("region")).agg(F.count("*").alias("n"))


@query("with x as (select vec_id as id, label, list_transform(embedding, lambda e: cast(e as double)) as v from embeddings), lm as (select id as lid, v as z from x order by md5('0:' || id), id limit 20), c as (select id, label, arg_min(lid, (d, lid)) as lid from (select x.id, x.label, lm.lid, sqrt(list_sum(list_transform(list_zip(x.v, lm.z), lambda t: (t[1] - t[2]) * (t[1] - t[2])))) as d from x, lm) group by id, label), n as (select lid, label, count(*) as n from c group by 1, 2) select lid, sum(n) :: bigint as size, round(max(n) / sum(n), 6) + 0.0 as purity from n group by lid")
def op_label_impurity(s, d):
    """Share of the commonest label in each landmark's cell."""
    p = R.vectors(s, d)
    ids, z = L.vectors_of(p, L.random_landmarks(p, 20))
    c = M.assign(p, ids, z).join(R.table(s, d, "embeddings").select(F.col("vec_id").alias("id"), "label"), "id").groupBy("lid", "label").agg(F.count("*").alias("n"))
    return c.groupBy("lid").agg(F.sum("n").alias("size"), r6(F.max("n") / F.sum("n")).alias("purity"))


@query("select id, bad from (select event_id as id, value is null or isnan(value) as bad from events) where not bad")
def op_reject_nulls(s, d):
    good, _ = R.validate(R.plane(s, d), 2)
    return good.select("id", F.lit(False).alias("bad"))


# streams over the events folder


def plane_stream(s: SparkSession, d: str) -> DataFrame:
    path = f"{d}/events.parquet"
    raw = s.readStream.schema(s.read.parquet(path).schema).option("maxFilesPerTrigger", 4).parquet(f"{d}/events.parque[t]")  # a pattern: the table may be one file
    return raw.select(F.col("event_id").alias("id"), F.array(F.col("value") / 100.0, F.lit(3.0) * R.day_fraction(F.col("ts"))).alias("vec"), F.to_timestamp(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSS")).alias("ts"), "user_id", "event_type")


def plane_stream_cut(s, d):
    """The event stream, the same rows as a table, and the time that ends the first four fifths of their span."""
    stream = plane_stream(s, d)
    e = R.table(s, d, "events").select(F.col("event_id").alias("id"), F.to_timestamp(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSS")).alias("ts"))
    points = R.plane(s, d).join(e, "id")
    low, high = e.agg(F.min(F.unix_micros("ts")), F.max(F.unix_micros("ts"))).first()
    return stream, points, F.timestamp_micros(F.lit(int(low + 0.8 * (high - low))))


def embedded_stream(s, d):
    _, m = plane_model(s, d)
    return X.stream_extend(plane_stream(s, d), m, 2, reach=0.3), m


@query(f"with {PLANE_SQL} select id, lid as nearest_lid, round(d, 6) + 0.0 as d_min, d > 0.3 as extrapolated from v")
def stream_extend(s, d):
    """Embedding of the event stream (coordinates are held against the batch form by the tests)."""
    return X.run_available(embedded_stream(s, d)[0], "extend").select("id", "nearest_lid", r6(F.col("d_min")).alias("d_min"), "extrapolated")


@query(f"with {PLANE_SQL} select strftime(ts, '%Y-%m-%d') as day, count(*) as n, sum(case when d > 0.3 then 1 else 0 end) :: bigint as outliers from v group by 1")
def stream_window_outliers(s, d):
    out = X.run_available(X.outlier_rate(embedded_stream(s, d)[0]), "outliers", "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n", "outliers")


@query("with e as (select user_id, ts, case when ts - lag(ts) over w < interval 2 hours then 0 else 1 end as new from events window w as (partition by user_id order by ts)), g as (select user_id, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from e), n as (select user_id, k, count(*) as n from g group by 1, 2) select user_id, count(*) as sessions, sum(n) :: bigint as events, max(n) as longest from n group by user_id")
def stream_session(s, d):
    """Sessions of each user (gap two hours), from session windows."""
    out = X.run_available(X.sessions(plane_stream(s, d)), "sessions", "complete")
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest"))


@query("select event_id as id from events")
def stream_late(s, d):
    """Ids once each within the watermark, from a stream that brings every event twice."""
    x = plane_stream(s, d).select("id", "ts")
    return X.run_available(X.once(x.union(plane_stream(s, d).select("id", "ts")), "60 days"), "late").select("id")


@query("with e as (select event_id as id, user_id, ts, event_type from events) select a.id as error_id, b.id as buy_id from e a join e b on a.user_id = b.user_id and a.event_type = 'error' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def stream_interval_join(s, d):
    x = plane_stream(s, d)
    return X.run_available(X.purchases_after_errors(x.where("event_type = 'error'"), plane_stream(s, d).where("event_type = 'purchase'"), late="60 days"), "joined").select("error_id", "buy_id")


@query()
def stream_state(s, d):
    """Basin changes of each user's trajectory by the stateful processor (batch form: ``state_batch``)."""
    e, _ = embedded_stream(s, d)
    try:
        s.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
        return X.run_available(X.basin_changes(e, late="60 days", idle_ms=366 * 86_400_000), "state")
    finally:
        s.conf.unset("spark.sql.streaming.stateStore.providerClass")


@query()
def state_batch(s, d):
    p, m = plane_model(s, d)
    e = R.table(s, d, "events").select(F.col("event_id").alias("id"), "user_id", "ts")
    return X.basin_changes_batch(M.extend(p, m, 2).join(e, "id"))


# SQL surface


@query(f"with {PLANE_SQL} select id, lid, 2 as modes from v")
def udtf_embed(s, d):
    """The table function over every event (rows per event), with the nearest landmark by SQL function."""
    p, m = plane_model(s, d)
    sql_surface.register_model(s, m, 2)
    p.createOrReplaceTempView("plane_points")
    return s.sql("select id, nearest_landmark(any_value(vec)) as lid, cast(count(*) as int) as modes from plane_points, lateral embed_point(vec) group by id")


@query(core.WITHIN_SQL)
def udf_distance(s, d):
    sql_surface.register_distances(s)
    users(s, d).createOrReplaceTempView("user_points")
    return s.sql(f"select i, j, round(d, 6) + 0.0D as d from (select a.id as i, b.id as j, euclid(a.vec, b.vec) as d from user_points a join user_points b on a.id < b.id) where d <= {NEAR}")


@query(f"with {LM_SQL}, o as (select i, j, d from pr union all select j, i, d from pr union all select id, id, 0.0 from p), c as (select a.lid, a.id, sum(o.d) as cost from v a join v b on a.lid = b.lid join o on o.i = a.id and o.j = b.id group by a.lid, a.id) select lid, arg_min(id, (round(cost, 9), id)) as medoid from c group by lid")
def udaf_medoid(s, d):
    """Medoid of each cell as a grouped Arrow aggregate (cells of task size; ``medoid_update`` is the split form)."""
    p, _, _, cells = user_cells(s, d)

    def medoid(key, t):
        x, ids = P.matrix(t["vec"]), t["id"].to_numpy()
        cost = np.round(D.euclidean_block(x, x).sum(1), 9)
        return pa.table({"lid": pa.array([key[0].as_py()]), "medoid": pa.array([ids[np.lexsort((ids, cost))[0]]])})

    return p.join(cells.select("id", "lid"), "id").groupBy("lid").applyInArrow(medoid, "lid long, medoid long")
