"""Operators around the methods, each a DataFrame query beside its SQL: scans, joins, aggregates, windows, set operations,
scalar families, Python surfaces, streams and sinks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import sql_uniform, uniform
from ..functions.vectors import nearest
from ..operators import candidates, freq, lloyd, scale, seed
from ..session import ship
from ..sources import io
from ..sources.io import table
from ..sources.workloads import load
from ..streaming import windows
from . import queries as q

Q: dict[str, tuple] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = (f, sql)
        return f

    return add


@query("ops_scan_prune", "select count(*) as n, round(sum(l_quantity), 2) as qty, round(max(l_extendedprice), 2) as top from lineitem")
def scan_prune(spark, sf):
    return table(spark, sf, "lineitem").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.max("l_extendedprice"), 2).alias("top"))


@query("ops_filter_pushdown", "select l_returnflag, count(*) as n from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_quantity < 24 group by l_returnflag")
def filter_pushdown(spark, sf):
    day = lambda d: F.lit(d).cast("timestamp_ntz")
    rows = table(spark, sf, "lineitem").where((F.col("l_shipdate") >= day("1995-01-01")) & (F.col("l_shipdate") < day("1996-01-01")) & (F.col("l_quantity") < 24))
    return rows.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@query("ops_case_in_like", "select case when p_type like '%STEEL%' then 'steel' when p_size in (1, 2, 3) then 'small' when p_retailprice between 1000 and 1500 then 'middle' else 'other' end as kind, count(*) as n from part group by 1")
def case_in_like(spark, sf):
    kind = F.when(F.col("p_type").like("%STEEL%"), "steel").when(F.col("p_size").isin(1, 2, 3), "small").when(F.col("p_retailprice").between(1000, 1500), "middle").otherwise("other")
    return table(spark, sf, "part").groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("n"))


@query("ops_join_inner", "select o_orderstatus, count(*) as n, round(sum(l_quantity), 2) as qty from lineitem join orders on l_orderkey = o_orderkey group by o_orderstatus")
def join_inner(spark, sf):
    j = table(spark, sf, "lineitem").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("ops_join_left", "select c_custkey, count(o_orderkey) as n from customer left join orders on c_custkey = o_custkey group by c_custkey")
def join_left(spark, sf):
    j = table(spark, sf, "customer").join(table(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left")
    return j.groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("ops_join_full", "select count(*) as n, count(o_orderkey) as orders, count(l_orderkey) as lines, count(case when o_orderkey is not null and l_orderkey is not null then 1 end) as met from orders full join lineitem on o_orderkey = l_orderkey and o_orderdate::DATE = l_shipdate::DATE")
def join_full(spark, sf):
    """Lines that left on the day of their order; most orders and lines have no such partner."""
    o, line = table(spark, sf, "orders"), table(spark, sf, "lineitem")
    same_day = (F.col("o_orderkey") == F.col("l_orderkey")) & (F.col("o_orderdate").cast("date") == F.col("l_shipdate").cast("date"))
    met = F.count_if(F.col("o_orderkey").isNotNull() & F.col("l_orderkey").isNotNull()).alias("met")
    return o.join(line, same_day, "full").agg(F.count(F.lit(1)).alias("n"), F.count("o_orderkey").alias("orders"), F.count("l_orderkey").alias("lines"), met)


@query("ops_join_semi", "select doc_id, n_chars from documents where doc_id in (select doc_id from labels)")
def join_semi(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "n_chars").join(table(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")


@query("ops_join_anti", "select doc_id, n_chars from documents where doc_id not in (select doc_id from labels)")
def join_anti(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "n_chars").join(table(spark, sf, "labels").select("doc_id"), "doc_id", "left_anti")


_BRAND = "select p_brand, count(*) as n, round(sum(l_extendedprice), 2) as total from lineitem join part on l_partkey = p_partkey group by p_brand"


def _hinted(hint: str):
    def run(spark, sf):
        parts = table(spark, sf, "part").select("p_partkey", "p_brand").hint(hint)
        j = table(spark, sf, "lineitem").select("l_partkey", "l_extendedprice").join(parts, F.col("l_partkey") == F.col("p_partkey"))
        return j.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))

    return run


for _name, _hint in (("broadcast", "broadcast"), ("merge", "merge"), ("hash", "shuffle_hash")):
    Q[f"ops_join_{_name}"] = (_hinted(_hint), _BRAND)


@query("ops_join_theta_nearest", f"with {q.sql_points('W8')}, {q.sql_first(3, 2)}, {q.sql_assign(2)} select row_key, g from a")
def join_theta_nearest(spark, sf):
    """Nearest of k rows that are data, not literals: they meet every point as one array, and the choice is made within the row."""
    points = scale.prepare(load(spark, sf, "W8"))[0]
    c = spark.createDataFrame([(g, float(v[0]), float(v[1])) for g, v in enumerate(seed.initial(points, 3))], "g int, c0 double, c1 double")
    near = c.agg(F.collect_list(F.struct("g", "c0", "c1")).alias("near"))  # one row of k
    d2 = lambda v: (F.col("z0") - v["c0"]) * (F.col("z0") - v["c0"]) + (F.col("z1") - v["c1"]) * (F.col("z1") - v["c1"])
    best = F.array_min(F.transform("near", lambda v: F.struct(d2(v).alias("d"), v["g"].alias("g"))))
    return points.join(F.broadcast(near)).select("row_key", best["g"].alias("g"))


@query("ops_join_range_cdf", f"with p as (select l_returnflag as f, count(*)::DOUBLE as n from lineitem group by 1), c as (select f, sum(n) over (order by f) / sum(n) over () as hi from p), t as (select range as i, {sql_uniform(chr(39) + 'cdf' + chr(39), 'range')} as u from range(500)) select i, min(f) as f from t join c on u <= hi group by i")
def join_range_cdf(spark, sf):
    p = table(spark, sf, "lineitem").groupBy(F.col("l_returnflag").alias("f")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    every = Window.orderBy("f")  # one row per flag
    c = p.select("f", (F.sum("n").over(every) / F.sum("n").over(Window.partitionBy(F.lit(0)))).alias("hi"))
    t = spark.range(500).select(F.col("id").alias("i"), uniform("cdf", F.col("id")).alias("u"))
    return t.join(F.broadcast(c), F.col("u") <= F.col("hi")).groupBy("i").agg(F.min("f").alias("f"))


@query("ops_join_interval", "select a.event_type, count(*) as n from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour group by a.event_type")
def join_interval(spark, sf):
    """Pairs of one user's events within an hour: an equi-join on hour buckets, then the exact condition."""
    e = table(spark, sf, "events").select("user_id", "ts", "event_type").withColumn("h", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000))
    late = e.select(F.col("user_id").alias("u"), F.col("ts").alias("t2"), F.col("h").alias("hb"))
    late = late.withColumn("hb", F.explode(F.array(F.col("hb"), F.col("hb") - 1)))
    j = e.join(late, (F.col("user_id") == F.col("u")) & (F.col("h") == F.col("hb")) & (F.col("t2") > F.col("ts")) & (F.col("t2") <= F.col("ts") + F.expr("interval 1 hour")))
    return j.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("ops_join_asof", "select e.event_id, (select max(p.ts) from events p where p.user_id = e.user_id and p.event_type = 'purchase' and p.ts < e.ts) as last_purchase from events e")
def join_asof(spark, sf):
    """The latest earlier purchase of the user: a running maximum over each user's events."""
    e = table(spark, sf, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), "ts")
    strictly = Window.partitionBy("user_id").orderBy("us").rangeBetween(Window.unboundedPreceding, -1)
    return e.select("event_id", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(strictly).alias("last_purchase"))


@query("ops_agg_basic", "select l_returnflag, l_linestatus, round(sum(l_quantity), 2) as qty, round(avg(l_discount), 6) as disc, count(*) as n, min(l_tax) as low, max(l_tax) as high from lineitem group by 1, 2")
def agg_basic(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count(F.lit(1)).alias("n"), F.min("l_tax").alias("low"), F.max("l_tax").alias("high")
    )


@query("ops_agg_distinct", "select event_type, count(distinct user_id) as users from events group by event_type")
def agg_distinct(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("ops_agg_countif", "select user_id, count(*) filter (event_type = 'purchase') as bought, count(*) filter (value > 50) as large from events group by user_id")
def agg_countif(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "purchase").alias("bought"), F.count_if(F.col("value") > 50).alias("large"))


@query("ops_agg_minby", "select event_type, arg_min(event_id, (value, event_id)) as least, arg_max(event_id, (value, event_id)) as most from events group by event_type")
def agg_minby(spark, sf):
    key = F.struct("value", "event_id")
    return table(spark, sf, "events").groupBy("event_type").agg(F.min_by("event_id", key).alias("least"), F.max_by("event_id", key).alias("most"))


@query("ops_agg_approx")
def agg_approx(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


_YEAR = "year(l_shipdate)"


def _flags(spark, sf):
    return table(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", F.year("l_shipdate").alias("y"), "l_quantity")


@query("ops_cube", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def cube(spark, sf):
    return _flags(spark, sf).cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@query("ops_rollup", f"select l_returnflag, {_YEAR}::INT as y, round(sum(l_quantity), 2) as qty from lineitem group by rollup (l_returnflag, {_YEAR})")
def rollup(spark, sf):
    return _flags(spark, sf).rollup("l_returnflag", "y").agg(F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("ops_grouping_sets", f"select l_returnflag, {_YEAR}::INT as y, count(*) as n from lineitem group by grouping sets ((l_returnflag), ({_YEAR}))")
def grouping_sets(spark, sf):
    return _flags(spark, sf).groupingSets([[F.col("l_returnflag")], [F.col("y")]], "l_returnflag", "y").agg(F.count(F.lit(1)).alias("n"))


@query("ops_pivot", "select l_returnflag, count(*) filter (l_linestatus = 'F') as f, count(*) filter (l_linestatus = 'O') as o from lineitem group by l_returnflag")
def pivot(spark, sf):
    p = _flags(spark, sf).groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))
    return p.select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


_CUST = "partition by o_custkey order by o_totalprice desc, o_orderkey"


@query("ops_win_rank", f"select o_orderkey, row_number() over ({_CUST}) as rn, rank() over (partition by o_custkey order by o_orderpriority) as rk, dense_rank() over (partition by o_custkey order by o_orderpriority) as dr from orders")
def win_rank(spark, sf):
    w, p = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"))


@query("ops_win_lag", "select event_id, round(value - lag(value) over w, 6) as change, lead(event_id) over w as next_id from events window w as (partition by user_id order by ts, event_id)")
def win_lag(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 6).alias("change"), F.lead("event_id").over(w).alias("next_id"))


@query("ops_win_running", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows unbounded preceding), 4) as run from events")
def win_running(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, sf, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("run"))


@query("ops_win_range", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as day_n from events")
def win_range(spark, sf):
    e = table(spark, sf, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)).alias("day_n"))


@query("ops_win_ntile", "select event_id, ntile(4) over (partition by event_type order by value, event_id)::INT as quarter from events")
def win_ntile(spark, sf):
    return table(spark, sf, "events").select("event_id", F.ntile(4).over(Window.partitionBy("event_type").orderBy("value", "event_id")).alias("quarter"))


@query("ops_sort_limit", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25 offset 5")
def sort_limit(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(25)


@query("ops_topk_group", "select p_brand, p_partkey from (select p_brand, p_partkey, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as rn from part) where rn <= 3")
def topk_group(spark, sf):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, sf, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("p_brand", "p_partkey")


_A, _B = "select p_size as v from part where p_size % 2 = 0", "select p_size as v from part where p_size % 3 = 0"


def _sides(spark, sf):
    p = table(spark, sf, "part").select(F.col("p_size").alias("v"))
    return p.where("v % 2 = 0"), p.where("v % 3 = 0")


@query("ops_union", f"select v, count(*) as n from ({_A} union all {_B}) group by v")
def union(spark, sf):
    a, b = _sides(spark, sf)
    return a.unionByName(b).groupBy("v").agg(F.count(F.lit(1)).alias("n"))


Q["ops_intersect"] = (lambda spark, sf: _sides(spark, sf)[0].intersect(_sides(spark, sf)[1]), f"{_A} intersect {_B}")
Q["ops_except"] = (lambda spark, sf: _sides(spark, sf)[0].subtract(_sides(spark, sf)[1]), f"{_A} except {_B}")
Q["ops_intersect_all"] = (lambda spark, sf: _sides(spark, sf)[0].intersectAll(_sides(spark, sf)[1]), f"{_A} intersect all {_B}")
Q["ops_except_all"] = (lambda spark, sf: _sides(spark, sf)[0].exceptAll(_sides(spark, sf)[1]), f"{_A} except all {_B}")


@query("ops_changed_labels", f"with {q.sql_points('W8')}, {q.sql_first(3, 2)}, {q.sql_lloyd(2, 2, 3)} select a2.row_key, a1.g as old_g, a2.g as new_g from a1 join a2 using (row_key) where a1.g <> a2.g")
def changed_labels(spark, sf):
    """Labels that one Lloyd step changes."""
    points = scale.prepare(load(spark, sf, "W8"))[0]
    c = seed.initial(points, 3)
    new, _ = lloyd.step(points, c)
    old = lloyd.assign(points, c).select("row_key", F.col("g").alias("old_g"))
    return old.join(lloyd.assign(points, new).select("row_key", F.col("g").alias("new_g")), "row_key").where("old_g <> new_g")


@query("ops_math", "select l_orderkey, l_partkey, l_suppkey, l_linenumber, round(sin(l_quantity) + cos(l_discount) + sqrt(l_tax) + exp(-l_discount) + log2(l_quantity + 1), 6) + 0.0 as v, ceil(l_extendedprice)::BIGINT as c, round(atan2(l_tax, l_discount + 1), 6) + 0.0 as a from lineitem")
def math_(spark, sf):
    col = F.col
    v = F.sin("l_quantity") + F.cos("l_discount") + F.sqrt("l_tax") + F.exp(-col("l_discount")) + F.log2(col("l_quantity") + 1)
    return table(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", (F.round(v, 6) + 0.0).alias("v"), F.ceil("l_extendedprice").alias("c"), (F.round(F.atan2("l_tax", col("l_discount") + 1), 6) + 0.0).alias("a"))


@query("ops_string", "select doc_id, length(text) as n, len(string_split(text, ' '))::BIGINT as words, md5(text) as h, lower(substr(text, 1, 3)) as head from documents")
def string_(spark, sf):
    d = table(spark, sf, "documents")
    return d.select("doc_id", F.length("text").cast("long").alias("n"), F.size(F.split("text", " ")).cast("long").alias("words"), F.md5("text").alias("h"), F.lower(F.substring("text", 1, 3)).alias("head"))


@query("ops_date", "select o_orderkey, year(o_orderdate)::INT as y, dayofweek(o_orderdate)::INT + 1 as dow, date_diff('day', date '1992-01-01', o_orderdate::DATE)::INT as days, epoch_us(o_orderdate) as us from orders")
def date_(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.year(d).alias("y"), F.dayofweek(d).alias("dow"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).alias("days"), F.unix_micros(d.cast("timestamp")).alias("us"))


@query("ops_bits", "select o_orderkey as i, (o_orderkey & 12) as a, (o_orderkey | 3) as o, xor(o_orderkey, 5) as x, (o_orderkey >> 1) as s, bit_count(o_orderkey)::INT as b from orders")
def bits(spark, sf):
    i = F.col("o_orderkey")
    return table(spark, sf, "orders").select(i.alias("i"), i.bitwiseAND(F.lit(12)).alias("a"), i.bitwiseOR(F.lit(3)).alias("o"), i.bitwiseXOR(F.lit(5)).alias("x"), F.shiftright(i, 1).alias("s"), F.bit_count(i).alias("b"))


@query("ops_array", "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) as norm2, round(list_max(embedding)::DOUBLE, 6) as top, (list_position(embedding, list_max(embedding)))::BIGINT as at from embeddings")
def array_(spark, sf):
    e = table(spark, sf, "embeddings")
    norm2 = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return e.select("vec_id", F.round(norm2, 5).alias("norm2"), F.round(F.array_max("embedding").cast("double"), 6).alias("top"), F.array_position("embedding", F.array_max("embedding")).alias("at"))


@query("ops_map", "select user_id, key as event_type, value as n from (select user_id, unnest(map_entries(map_from_entries(list((event_type, n)))), recursive := true) from (select user_id, event_type, count(*) as n from events group by 1, 2) group by user_id) t(user_id, key, value)")
def map_(spark, sf):
    n = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))  # as many entries as event types
    return m.select("user_id", F.explode("m").alias("event_type", "n"))


@query("ops_json", "select event_id, (props::JSON ->> '$.k')::INT as k from events")
def json_(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("ops_explode", "select vec_id, (i - 1)::INT as i, round(embedding[i]::DOUBLE, 6) as v from (select vec_id, embedding, unnest(range(1, len(embedding) + 1)) as i from embeddings)")
def explode_(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v"))
    return e.select("vec_id", "i", F.round(F.col("v").cast("double"), 6).alias("v"))


@query("ops_pages", "select page_id, length(html) as n, len(regexp_extract_all(html, 'href='))::INT as links, len(string_split(url, '/'))::INT as depth from pages")
def pages(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.length("html").cast("long").alias("n"), F.regexp_count("html", F.lit("href=")).alias("links"), F.size(F.split("url", "/")).alias("depth"))


@query("ops_conversations", "select role, count(*) as turns, count(distinct conv_id) as convs, sum(length(text))::BIGINT as chars from conversations group by role")
def conversations(spark, sf):
    return table(spark, sf, "conversations").groupBy("role").agg(F.count(F.lit(1)).alias("turns"), F.count_distinct("conv_id").alias("convs"), F.sum(F.length("text")).alias("chars"))


@query("ops_udf_assign", f"with {q.sql_points('W8')}, {q.sql_first(3, 2)}, {q.sql_assign(2)} select row_key, g from a")
def udf_assign(spark, sf):
    """Assignment by a vectorised Python function; the native expression is the main path."""
    points = scale.prepare(load(spark, sf, "W8"))[0]
    c = seed.initial(points, 3)

    @F.pandas_udf("int")
    def label(a: pd.Series, b: pd.Series) -> pd.Series:
        x = np.stack([a.to_numpy(), b.to_numpy()], axis=1)
        return pd.Series(((x[:, None, :] - c[None, :, :]) ** 2).sum(axis=2).argmin(axis=1).astype("int32"))

    return points.select("row_key", label("z0", "z1").alias("g"))


@query("ops_udaf_sketch", f"with {q.sql_points('W8')}, {q.sql_freq(8, 2)}, {q.sql_sketch(2)} select j, {q.r6('re')} as re, {q.r6('im')} as im from zx")
def udaf_sketch(spark, sf):
    """A sketch as a two-stage Python aggregate: partial sums per partition, added up per frequency."""
    points, w = scale.prepare(load(spark, sf, "W8"))[0], freq.matrix(8, 2)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            t = np.stack([b.column(c).to_numpy() for c in ("z0", "z1")], axis=1) @ w.T
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(8)), pa.array(np.cos(t).sum(axis=0)), pa.array(np.sin(t).sum(axis=0)), pa.array(np.full(8, len(t)))], names=["j", "c", "s", "n"])

    sums = points.select("z0", "z1").mapInArrow(partial, "j long, c double, s double, n long").groupBy("j").agg(F.sum("c").alias("c"), F.sum("s").alias("s"), F.sum("n").alias("n"))
    return q.rounded(sums.select(F.col("j").cast("int").alias("j"), (F.col("c") / F.col("n")).alias("re"), (F.col("s") / F.col("n")).alias("im")), "re", "im")


@query("ops_udtf_candidates", f"with {q.sql_model()} select g, r, {q.r6('v0')} as c0, {q.r6('v1')} as c1 from cand")
def udtf_candidates(spark, sf):
    """Candidates by a Python table function, one call per centroid."""
    ship(spark)

    @F.udtf(returnType="g int, r int, c0 double, c1 double")
    class Around:
        def eval(self, g: int, c0: float, c1: float):
            for r in range(4):
                jitter = [0.0 if r == 0 else 0.2 * candidates.py_normal("c", 42, 0, g, r, i) for i in range(2)]
                yield g, r, c0 + jitter[0], c1 + jitter[1]

    spark.udtf.register("candidates_around", Around)
    points = scale.prepare(load(spark, sf, "W8"))[0]
    spark.createDataFrame([(g, float(c[0]), float(c[1])) for g, c in enumerate(seed.initial(points, 3))], "g int, c0 double, c1 double").createOrReplaceTempView("seed_centroids")
    out = spark.sql("select t.* from seed_centroids s, lateral candidates_around(s.g, s.c0, s.c1) t")
    return q.rounded(out, "c0", "c1")


@query("ops_sql_function", "select p_partkey as g, round(pow(p_size - 1.5, 2) + pow(p_retailprice * 0.5, 2), 6) + 0.0 as cost from part")
def sql_function(spark, sf):
    """A SQL function over views: squared distance of two complex numbers."""
    spark.sql("create or replace temporary function sketch_distance(a double, b double, c double, d double) returns double return (a - c) * (a - c) + (b - d) * (b - d)")
    table(spark, sf, "part").createOrReplaceTempView("parts")
    return spark.sql("select p_partkey as g, round(sketch_distance(cast(p_size as double), p_retailprice * cast(0.5 as double), 1.5, 0), 6) + 0.0 as cost from parts")


_W4 = windows.frequencies(4)
_AGGS = "count(*) as n, " + ", ".join(f"round(avg(cos(value / 100 * {w!r})), 6) + 0.0 as re{j}, round(avg(sin(value / 100 * {w!r})), 6) + 0.0 as im{j}" for j, w in enumerate(_W4))


def _stream(length: str, slide: str | None, sql: str):
    def run(spark, sf):
        out = windows.run_to_memory(windows.windowed(windows.events(spark, f"{sf}/events.parquet"), _W4, length, slide))
        return q.rounded(out, *[c for c in out.columns if c[:2] in ("re", "im")])

    return run, sql


_DAY = "strftime(time_bucket(interval 1 day, ts), '%Y-%m-%d %H:%M')"
Q["stream_window_sketch"] = _stream("1 day", None, f"select {_DAY} as start, {_AGGS} from events group by 1")
Q["ops_stream_tumbling"] = _stream("6 hours", None, f"select strftime(time_bucket(interval 6 hours, ts, timestamp '1970-01-01'), '%Y-%m-%d %H:%M') as start, {_AGGS} from events group by 1")
Q["ops_stream_sliding"] = _stream("2 days", "1 day", f"select strftime(time_bucket(interval 1 day, ts) - to_days(k::INT), '%Y-%m-%d %H:%M') as start, {_AGGS} from events, range(2) t(k) group by 1")


@query("ops_stream_session", "with s as (select user_id, value, sum(case when lag_ts is null or ts >= lag_ts + interval 30 minutes then 1 else 0 end) over (partition by user_id order by ts, event_id) as k from (select *, lag(ts) over (partition by user_id order by ts, event_id) as lag_ts from events)) select user_id, n, count(*) as sessions from (select user_id, k, count(*) as n from s group by 1, 2) group by 1, 2")
def stream_session(spark, sf):
    """Sessions per user, as a stream in complete mode; then how many have how many events."""
    out = windows.run_to_table(windows.sessions(windows.events(spark, f"{sf}/events.parquet")).select("user_id", "n"), "complete")
    return out.groupBy("user_id", "n").agg(F.count(F.lit(1)).alias("sessions"))


@query("ops_stream_dedup", "select event_type, count(distinct event_id) as n from events group by event_type")
def stream_dedup(spark, sf):
    """The table streamed twice: every event counts once."""
    rows = windows.events(spark, f"{sf}/events.parquet").withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    out = windows.run_to_table(windows.deduplicated(rows).select("event_id", "event_type"))
    return out.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("ops_sample_bernoulli", f"select event_id from events where {sql_uniform(chr(39) + 'bern' + chr(39), 'event_id')} < 0.1")
def sample_bernoulli(spark, sf):
    return table(spark, sf, "events").select("event_id").where(uniform("bern", F.col("event_id")) < 0.1)


@query("ops_sample_stratified", f"select event_id, event_type from events where {sql_uniform(chr(39) + 'str' + chr(39), 'event_id')} < case event_type when 'purchase' then 0.5 else 0.05 end")
def sample_stratified(spark, sf):
    share = F.when(F.col("event_type") == "purchase", 0.5).otherwise(0.05)
    return table(spark, sf, "events").select("event_id", "event_type").where(uniform("str", F.col("event_id")) < share)


@query("ops_sink_roundtrip", "select f as format, count(*) as n, sum(p_partkey)::BIGINT as keys from part, unnest(['parquet', 'orc', 'json', 'csv']) t(f) group by f")
def sink_roundtrip(spark, sf):
    """Assignments written partitioned by label and read back, in four formats."""
    import uuid

    root = f"{spark.conf.get('spark.checkpoint.dir', None) or spark.conf.get('spark.sql.warehouse.dir')}/roundtrip-{uuid.uuid4().hex[:8]}"
    points = scale.prepare(load(spark, sf, "W8"))[0]
    g, _ = nearest(["z0", "z1"], seed.initial(points, 3))
    rows = points.select(F.col("row_key").cast("long").alias("row_key"), g.alias("g"))
    out = None
    for kind in ("parquet", "orc", "json", "csv"):
        io.write(rows, f"{root}/{kind}", kind, ("g",))
        back = io.read(spark, f"{root}/{kind}", kind, "row_key long, g int").agg(F.count(F.lit(1)).alias("n"), F.sum("row_key").alias("keys")).select(F.lit(kind).alias("format"), "n", "keys")
        out = back if out is None else out.unionByName(back)
    return out


QUERIES = {n: f for n, (f, _) in Q.items()}
ORACLE_SQL = {n: s for n, (_, s) in Q.items() if s is not None}
