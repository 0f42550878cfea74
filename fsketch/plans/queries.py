"""Queries of the method, each beside SQL that computes the same from the raw tables.

The model queries run on parts (2 features), with k centroids that are the first rows by hash, D candidates around each
and m frequencies; the SQL is put together from common table expressions.
"""

from __future__ import annotations

import math
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import py_normal, sql_normal, sql_uniform
from ..functions.vectors import feature_names
from ..operators import baselines, bounds, candidates, freq, hadamard, lloyd, measures, qubo, resources, sample, scale, seed, sketch, solve, variational
from ..operators.noise import Noise
from ..sources.io import table
from ..sources.workloads import load
from . import views
from .pipeline import cluster, compressive_baseline

K, D, M = 3, 4, 24
JITTER = 0.2
NOISY = Noise(p2=0.002)

# ---- SQL pieces ----
LINE_KEY = "concat_ws('|', l_orderkey::VARCHAR, l_partkey::VARCHAR, l_suppkey::VARCHAR, l_linenumber::VARCHAR, strftime(l_shipdate, '%Y-%m-%d %H:%M:%S'), l_extendedprice::VARCHAR)"
POINTS = {
    "W8": ("p_partkey::VARCHAR", ["p_size", "p_retailprice"], "part"),
    "W12": (LINE_KEY, ["l_quantity", "l_extendedprice", "l_discount"], "lineitem"),
    "W10": ("event_id::VARCHAR", ["value", "hour(ts)", "(props::JSON ->> '$.k')::INT", "user_id"], "events"),
    "W9": ("vec_id::VARCHAR", [f"embedding[{i + 1}]" for i in range(22)], "embeddings"),
}

_DAY = lambda c: f"date_diff('day', DATE '1992-01-01', {c}::DATE)"
_CODE = lambda c: f"(('0x' || substr(md5({c}), 1, 4))::BIGINT % 16)"
_SHAPE = lambda table_, key, n: f"(select *, {key} as key from {table_} order by {sql_uniform(chr(39) + 'shape' + chr(39), key)}, {key} limit {n})"


def _q(*parts: str) -> list[str]:
    """Quoted where not an expression: the first parts of a draw are names."""
    return [f"'{p[1:]}'" if p[0] == "=" else p for p in parts]


def _moon(noise: float) -> list[str]:
    a, lower = f"({math.pi!r} * {sql_uniform(*_q('=moon', 'key'))})", "key % 2 = 1"
    return [
        f"case when {lower} then 1 - cos({a}) else cos({a}) end + {noise} * {sql_normal(*_q('=mx', 'key'))}",
        f"case when {lower} then 0.5 - sin({a}) else sin({a}) end + {noise} * {sql_normal(*_q('=my', 'key'))}",
    ]


def _blob(varied: bool) -> list[str]:
    group = "(l_returnflag || l_linestatus)"
    spread = f"(0.3 + {sql_uniform(*_q('=spread', group))})" if varied else "0.5"
    return [f"20 * {sql_uniform(*_q('=centre', '=' + t, group))} + {spread} * {sql_normal(*_q('=blob', '=' + t, 'key'))}" for t in ("x", "y")]


def _ring() -> list[str]:
    angle, radius = f"({2 * math.pi!r} * {sql_uniform(*_q('=ring', 'key'))})", "(case when key % 2 = 0 then 1.0 else 0.5 end)"
    return [f"{radius}::DOUBLE * {f}({angle}) + 0.05 * {sql_normal(*_q('=ring', '=' + t, 'key', 'trunc(o_totalprice)::BIGINT'))}" for f, t in (("cos", "x"), ("sin", "y"))]


_T = f"(({_DAY('o_orderdate')} % 1000) / 1000.0::DOUBLE)"
_SPIRAL = [f"(1 + 9 * {_T}) * {f}(3 * {_T} + {2 * math.pi / 3!r} * (key % 3))" for f in ("cos", "sin")]
_WIDE = [
    *"l_quantity l_extendedprice l_discount l_tax l_linenumber o_totalprice c_nationkey c_acctbal p_size p_retailprice s_acctbal s_nationkey n_regionkey".split(),
    _DAY("l_shipdate"), _DAY("o_orderdate"), *[_CODE(c) for c in "l_returnflag l_linestatus o_orderpriority o_orderstatus c_mktsegment p_brand".split()], "length(p_type)", "1",
]
_TEXT = ["n_chars", "len(ws)", "len(list_distinct(ws)) / greatest(len(ws), 1)", "len(string_split(text, chr(10)))", "length(regexp_replace(text, '[^0-9]', '', 'g')) / greatest(length(text), 1)", "length(text) / greatest(len(ws), 1)", _CODE("lang"), "copies"]
POINTS |= {
    "W1": ("key::VARCHAR", _ring(), _SHAPE("orders", "o_orderkey", 300)), "W2": ("key::VARCHAR", _SPIRAL, _SHAPE("orders", "o_orderkey", 300)),
    "W3": ("key::VARCHAR", _moon(0.05), _SHAPE("orders", "o_orderkey", 400)), "W3b": ("key::VARCHAR", _moon(0.15), _SHAPE("orders", "o_orderkey", 400)),
    **{w: ("key", _blob(v), _SHAPE("lineitem", LINE_KEY, n)) for w, n, v in (("W4", 600, False), ("W5", 1200, True), ("W6", 2100, False))},
    "W7": (
        "c_custkey::VARCHAR", ["c_acctbal", "c_nationkey", *[f"coalesce({x}, 0)" for x in ("n", "a", "b", "s", "span")]],
        f"(customer left join (select o_custkey, count(*) as n, avg(o_totalprice) as a, max(o_totalprice) as b, sum(o_totalprice) as s, date_diff('day', min(o_orderdate)::DATE, max(o_orderdate)::DATE) as span from orders group by o_custkey) on c_custkey = o_custkey)",
    ),
    "W11": (
        "o_orderkey::VARCHAR", ["o_totalprice", _DAY("o_orderdate"), *[f"coalesce({x}, 0)" for x in ("n", "q", "p", "dc", "t", "span")]],
        "(orders left join (select l_orderkey, count(*) as n, sum(l_quantity) as q, avg(l_extendedprice) as p, avg(l_discount) as dc, avg(l_tax) as t, date_diff('day', min(l_shipdate)::DATE, max(l_shipdate)::DATE) as span from lineitem group by l_orderkey) on o_orderkey = l_orderkey)",
    ),
    "W13": (LINE_KEY, _WIDE, "(lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey)"),
    "W14": (LINE_KEY, ["l_quantity", "l_extendedprice"], "lineitem"), "W15": (LINE_KEY, ["l_quantity", "l_extendedprice", "l_tax"], "lineitem"),
    "W23": ("doc_id::VARCHAR", _TEXT, "(select *, string_split(text, ' ') as ws, count(*) over (partition by md5(text)) as copies from documents)"),
    "W24": ("page_id::VARCHAR", ["length(html)", "len(regexp_extract_all(html, '<[a-z]'))", "len(regexp_extract_all(html, 'href='))", "len(string_split(url, '/'))"], "pages"),
    "W24b": ("conv_id::VARCHAR", ["turns", "u", "a", "s"], "(select conv_id, count(*) as turns, " + ", ".join(f"sum(case when role = '{r}' then length(text) else 0 end) as {r[0]}" for r in ("user", "assistant", "system")) + " from conversations group by conv_id)"),
    "W24c": ("item_id::VARCHAR", ["length(text)"], "benchmark"),
}


def zs(d: int) -> list[str]:
    return [f"z{i}" for i in range(d)]


def sql_points(workload: str) -> str:
    """CTEs pts, st and z: points, moments and standardised points."""
    key, cols, source = POINTS[workload]
    d = range(len(cols))
    return (
        f"pts as (select {key} as row_key, {', '.join(f'({c})::DOUBLE as x{i}' for i, c in enumerate(cols))} from {source}), "
        f"st as (select {', '.join(f'avg(x{i}) as m{i}, stddev_pop(x{i}) as s{i}' for i in d)} from pts), "
        f"z as materialized (select row_key, {', '.join(f'x{i}' for i in d)}, {', '.join(f'(x{i} - m{i}) / case when s{i} > 0 then s{i} else 1 end as z{i}' for i in d)} from pts, st)"
    )


def sql_freq(m: int, d: int, seed_: int = 42) -> str:
    return f"w as materialized (select j::INT as j, {', '.join(sql_normal(chr(39) + 'w' + chr(39), str(seed_), 'j', str(c)) + f' as w{c}' for c in range(d))} from range({m}) t(j))"


def sql_dot(d: int, a: str = "z.z", b: str = "w.w") -> str:
    return " + ".join(f"{a}{i} * {b}{i}" for i in range(d))


def sql_distinct_first(k: int, d: int, seed_: int = 42, name: str = "c") -> str:
    """CTE: the first k distinct points by hash, numbered."""
    h = f"{sql_uniform(chr(39) + 's' + chr(39), str(seed_), 'row_key')}, row_key"
    once = f"(select *, row_number() over (partition by {', '.join(zs(d))} order by {h}) as _n from z)"
    return f"{name} as materialized (select g::INT as g, {', '.join(f'z{i} as c{i}' for i in range(d))} from (select *, row_number() over (order by {h}) - 1 as g from {once} where _n = 1) where g < {k})"


def sql_first(k: int, d: int) -> str:
    """CTE c: the first k points by hash, numbered."""
    return f"c as materialized (select g::INT as g, {', '.join(f'z{i} as c{i}' for i in range(d))} from (select *, row_number() over (order by {sql_uniform(chr(39) + 's' + chr(39), '42', 'row_key')}, row_key) - 1 as g from z) where g < {k})"


def sql_assign(d: int, name: str = "a", centres: str = "c") -> str:
    dist = " + ".join(f"(z{i} - c{i}) * (z{i} - c{i})" for i in range(d))
    return f"{name} as materialized (select row_key, {', '.join(f'x{i}, z{i}' for i in range(d))}, g, d2 from (select z.*, {centres}.g, {dist} as d2, row_number() over (partition by row_key order by {dist}, {centres}.g) as rn from z cross join {centres}) where rn = 1)"


def sql_candidates(d: int, per_group: int, centres: str = "c") -> str:
    cols = ", ".join(f"c{i} + case when r = 0 then 0 else {JITTER} * {sql_normal(chr(39) + 'c' + chr(39), '42', '0', 'g', 'r', str(i))} end as v{i}" for i in range(d))
    return f"cand as materialized (select g, r::INT as r, {cols} from {centres}, range({per_group}) t(r))"


def sql_features(d: int) -> str:
    return f"v as materialized (select g, r, j, cos({sql_dot(d, 'v', 'w')}) as re, sin({sql_dot(d, 'v', 'w')}) as im from cand cross join w)"


def sql_sketch(d: int) -> str:
    return f"zx as materialized (select j, avg(cos({sql_dot(d)})) as re, avg(sin({sql_dot(d)})) as im, count(*) as n from z cross join w group by j)"


def sql_cluster_sketch(d: int) -> str:
    return f"zg as materialized (select g, j, avg(cos({sql_dot(d, 'a.z')})) as re, avg(sin({sql_dot(d, 'a.z')})) as im, count(*) as n from a cross join w group by g, j)"


def sql_model(k: int = K, per_group: int = D, m: int = M, workload: str = "W8") -> str:
    d = len(POINTS[workload][1])
    return ", ".join([sql_points(workload), sql_freq(m, d), sql_first(k, d), sql_candidates(d, per_group), sql_features(d), sql_sketch(d)])


def sql_costs(d: int = 2) -> str:
    return f"{sql_assign(d)}, {sql_cluster_sketch(d)}, cost as materialized (select v.g, v.r, sum((v.re - zg.re) * (v.re - zg.re) + (v.im - zg.im) * (v.im - zg.im)) as cost from v join zg on zg.g = v.g and zg.j = v.j group by v.g, v.r)"


def r6(expr: str) -> str:
    return f"round({expr}, 6) + 0.0"


# ---- engine pieces ----
def rounded(df: DataFrame, *cols: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c), digits) + F.lit(0.0) for c in cols})


def _prepared(spark: SparkSession, sf: str, workload: str) -> DataFrame:
    return scale.prepare(load(spark, sf, workload))[0]


class _Parts:
    """The small model on a workload, as far as a query needs it."""

    def __init__(self, spark: SparkSession, sf: str, k: int = K, per_group: int = D, m: int = M, workload: str = "W8"):
        self.spark, self.k, self.m = spark, k, m
        self.points, self.scaler = scale.prepare(load(spark, sf, workload))
        self.w = freq.matrix(m, len(self.scaler.cols))
        self.centroids = seed.initial(self.points, k)
        self.sets = candidates.around(self.centroids, per_group, JITTER)

    def z(self) -> np.ndarray:
        return sketch.vector(sketch.exact(self.points, self.w), self.m)

    def model(self) -> qubo.Model:
        return qubo.joint(self.z(), self.sets, self.w)

    def zg(self) -> np.ndarray:
        return hadamard.estimate_clusters(lloyd.assign(self.points, self.centroids), self.w, None)[0]

    def costs(self) -> list[np.ndarray]:
        return qubo.grouped_costs(self.zg(), self.sets, self.w)


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame([tuple(v.item() if isinstance(v, np.generic) else v for v in r) for r in rows], schema)


# ---- queries: name -> (function, SQL or None) ----
Q: dict[str, tuple] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = (f, sql)
        return f

    return add


@query("std_stats", f"with {sql_points('W12')} select i::INT as i, n, round(m, 4) as mean, round(s, 4) as std from (select count(*) as n, [{', '.join(f'any_value(m{i})' for i in range(3))}] as ms, [{', '.join(f'any_value(s{i})' for i in range(3))}] as ss from pts, st), lateral (select unnest(range(3)) as i), lateral (select ms[i + 1] as m, ss[i + 1] as s)")
def std_stats(spark, sf):
    s = scale.fit(load(spark, sf, "W12"))
    return rounded(_frame(spark, [(i, s.n, float(s.mean[i]), float(s.std[i])) for i in range(3)], "i int, n long, mean double, std double"), "mean", "std", digits=4)


@query("std_project", f"with {sql_points('W8')} select row_key, {r6('z0')} as z0, {r6('z1')} as z1 from z")
def std_project(spark, sf):
    return rounded(_prepared(spark, sf, "W8").select("row_key", "z0", "z1"), "z0", "z1")


_FREQ = [sql_normal("'w'", "42", "p_partkey", str(c)) for c in range(2)]


@query("freq_draw", f"select p_partkey as j, {r6(_FREQ[0])} as w0, {r6(_FREQ[1])} as w1 from part")
def freq_draw(spark, sf):
    """The frequency numbered by each part's key."""
    w = freq.numbered(table(spark, sf, "part"), "p_partkey", 2)
    return rounded(w.select("j", F.get("w", 0).alias("w0"), F.get("w", 1).alias("w1")), "w0", "w1")


def _exact(workload: str, m: int, d: int, engine: str):
    sql = f"with {sql_points(workload)}, {sql_freq(m, d)}, {sql_sketch(d)} select j, {r6('re')} as re, {r6('im')} as im, n from zx"

    def run(spark, sf):
        return rounded(sketch.exact(_prepared(spark, sf, workload), freq.matrix(m, d), engine), "re", "im")

    return run, sql


Q["sketch_exact_part"] = _exact("W8", M, 2, "wide")
Q["sketch_exact_lineitem"] = _exact("W12", 12, 3, "wide")
Q["sketch_exact_events"] = _exact("W10", 16, 4, "arrow")
Q["sketch_exact_embeddings"] = _exact("W9", 66, 22, "auto")


@query("sketch_merge_by_flag", f"with {sql_points('W12')}, {sql_freq(8, 3)}, {sql_sketch(3)} select j, {r6('re')} as re, {r6('im')} as im, n from zx")
def sketch_merge_by_flag(spark, sf):
    """One sketch per return flag, merged: equal to the direct one."""
    points = _prepared(spark, sf, "W12")
    flags = table(spark, sf, "lineitem").select(F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate", "l_extendedprice")]).alias("_k"), F.ascii("l_returnflag").alias("g"))
    parts = sketch.per_cluster(points.join(flags, F.col("row_key") == F.col("_k")), freq.matrix(8, 3))
    return rounded(sketch.means(sketch.merge(parts.drop("g"))), "re", "im")


@query("centroid_sketch", f"with {sql_model()} select j, {r6('avg(re)')} as re, {r6('avg(im)')} as im from v where r = 0 group by j")
def centroid_sketch(spark, sf):
    p = _Parts(spark, sf)
    return rounded(sketch.to_frame(spark, sketch.of_centroids(p.centroids, p.w)), "re", "im")


@query("sketch_mismatch", f"with {sql_model()}, cs as (select j, avg(re) as re, avg(im) as im from v where r = 0 group by j) select {r6('sum((cs.re - zx.re) * (cs.re - zx.re) + (cs.im - zx.im) * (cs.im - zx.im))')} as mismatch from cs join zx using (j)")
def sketch_mismatch(spark, sf):
    p = _Parts(spark, sf)
    return rounded(_frame(spark, [(sketch.mismatch(p.z(), sketch.of_centroids(p.centroids, p.w)),)], "mismatch double"), "mismatch")


@query("kernel_error", f"with {sql_points('W8')}, {sql_freq(M, 2)}, s as (select * from z order by {sql_uniform(chr(39) + 's' + chr(39), '42', 'row_key')}, row_key limit 40), p as (select a.row_key as a, b.row_key as b, a.z0 - b.z0 as d0, a.z1 - b.z1 as d1 from s a join s b on a.row_key < b.row_key), q as (select a, b, avg(cos(d0 * w0 + d1 * w1)) as approx, any_value(exp(-(d0 * d0 + d1 * d1) / 2)) as exact from p cross join w group by a, b) select a, b, {r6('approx')} as approx, {r6('exact')} as exact, {r6('abs(approx - exact)')} as error from q")
def kernel_error(spark, sf):
    few = sample.shared(_prepared(spark, sf, "W8"), 40)
    return rounded(measures.kernel_error(few, freq.matrix(M, 2)), "approx", "exact", "error")


_H = sql_uniform("'s'", "42", "row_key")


@query("sample_shared", f"with {sql_points('W12')} select row_key from (select row_key, {_H} as h from z) order by h, row_key limit 256")
def sample_shared(spark, sf):
    return sample.shared(load(spark, sf, "W12").select("row_key"), 256)


@query("sample_per_frequency", f"with {sql_points('W12')}, s as (select row_key, row_number() over (order by {_H}, row_key) - 1 as r from pts) select row_key, (r // 64)::INT as j, (r % 64)::INT as pos from s where r < 512")
def sample_per_frequency(spark, sf):
    return sample.per_frequency(load(spark, sf, "W12").select("row_key"), 64, 8).select("row_key", "j", F.col("pos").cast("int").alias("pos"))


@query("sample_per_cluster", f"with {sql_points('W8')}, {sql_first(K, 2)}, {sql_assign(2)}, s as (select row_key, g, row_number() over (partition by g order by {_H}, row_key) - 1 as pos from a) select row_key, g, pos::INT as pos from s where pos < 16")
def sample_per_cluster(spark, sf):
    p = _Parts(spark, sf)
    return sample.per_group(lloyd.assign(p.points, p.centroids), 16).select("row_key", "g", F.col("pos").cast("int").alias("pos"))


_HAD = f"with {sql_points('W8')}, {sql_freq(8, 2)}, s as (select *, row_number() over (order by {_H}, row_key) - 1 as rn from z), b as (select (rn // 48)::INT as j, z0, z1 from s where rn < 384), h as materialized (select b.j, sum(cos({sql_dot(2, 'z')})) as c, sum(sin({sql_dot(2, 'z')})) as s from b join w using (j) group by b.j)"


@query("hadamard_ideal", _HAD + f" select j, {r6('(c + 16) / 64')} as re, {r6('s / 64')} as im from h")
def hadamard_ideal(spark, sf):
    rows = sample.per_frequency(_prepared(spark, sf, "W8"), 48, 8)
    return rounded(hadamard.expectation(rows, freq.draw(spark, 8, 2)).select("j", "re", "im"), "re", "im")


@query("hadamard_rescaled", _HAD + f" select j, {r6('c / 48')} as re, {r6('s / 48')} as im from h")
def hadamard_rescaled(spark, sf):
    """The padding cancels: the rescaled value is the plain mean of the sample."""
    return rounded(hadamard.estimate_sketch(_prepared(spark, sf, "W8"), 8, 48, None).select("j", "re", "im"), "re", "im")


def _coins(part: str, value: str) -> str:
    return f"(select 2.0 * count(*) filter ({sql_uniform(chr(39) + 'h' + chr(39), '42', chr(39) + part + chr(39), 'h.j', 't')} < (1 + {value}) / 2) / 1024 - 1 from range(1024) r(t))"


@query("hadamard_shots", _HAD + f" select j, {r6('64.0 / 48 * ' + _coins('re', '(c + 16) / 64') + ' - 16.0 / 48')} as re, {r6('64.0 / 48 * ' + _coins('im', 's / 64'))} as im from h")
def hadamard_shots(spark, sf):
    return rounded(hadamard.estimate_sketch(_prepared(spark, sf, "W8"), 8, 48, 1024).select("j", "re", "im"), "re", "im")


_REPS = 200
_HS = sql_uniform("'s'", "seed", "row_key")


@query("estimator_mse_bound", f"with {sql_points('W8')}, {sql_freq(8, 2)}, {sql_sketch(2)}, s as materialized (select * from (select t.seed, z.*, row_number() over (partition by t.seed order by {_HS}, row_key) as rn from z cross join range({_REPS}) t(seed)) where rn <= 48), e as (select s.seed, w.j, avg(cos({sql_dot(2, 's.z')})) as re, avg(sin({sql_dot(2, 's.z')})) as im from s cross join w group by s.seed, w.j) select zx.j, {r6('avg((e.re - zx.re) * (e.re - zx.re) + (e.im - zx.im) * (e.im - zx.im))')} as mse, {r6('any_value((1 - 48.0 / n) / 48 * n / (n - 1) * (1 - zx.re * zx.re - zx.im * zx.im))')} as expected from e join zx using (j) group by zx.j")
def estimator_mse_bound(spark, sf):
    """Mean squared error of subsample means over repeats, beside the variance of sampling without replacement."""
    points = _prepared(spark, sf, "W8")
    w = freq.matrix(8, 2)
    each = points.crossJoin(F.broadcast(spark.range(_REPS).withColumnRenamed("id", "g")))
    from pyspark.sql.window import Window

    from ..functions.hashing import uniform

    picked = each.withColumn("_r", F.row_number().over(Window.partitionBy("g").orderBy(uniform("s", F.col("g"), F.col("row_key")), "row_key"))).where("_r <= 48")
    got = sketch.means(sketch.per_cluster(picked, w, "wide")).select("j", "re", "im")
    exact = sketch.exact(points, w).select("j", F.col("re").alias("z_re"), F.col("im").alias("z_im"), F.col("n").alias("n"))
    err = (F.col("re") - F.col("z_re")) ** 2 + (F.col("im") - F.col("z_im")) ** 2
    expected = (1 - 48.0 / F.col("n")) / 48 * F.col("n") / (F.col("n") - 1) * (1 - F.col("z_re") ** 2 - F.col("z_im") ** 2)
    return rounded(got.join(F.broadcast(exact), "j").groupBy("j").agg(F.avg(err).alias("mse"), F.first(expected).alias("expected")), "mse", "expected")


@query("candidates_jitter", f"with {sql_model()} select g, r, {r6('v0')} as c0, {r6('v1')} as c1 from cand")
def candidates_jitter(spark, sf):
    out = candidates.to_frame(spark, _Parts(spark, sf).sets)
    return rounded(out.select("g", "r", F.get("c", 0).alias("c0"), F.get("c", 1).alias("c1")), "c0", "c1")


_LIN = f"b as materialized (select v.g, v.r, -2.0 / {K} * sum(v.re * zx.re + v.im * zx.im) as b from v join zx using (j) group by v.g, v.r), q as materialized (select x.g, x.r, y.g as g2, y.r as r2, sum(x.re * y.re + x.im * y.im) / {K * K} as q from v x join v y on x.j = y.j group by x.g, x.r, y.g, y.r)"


@query("qubo_linear", f"with {sql_model()}, {_LIN} select g, r, {r6('b')} as b from b")
def qubo_linear(spark, sf):
    return rounded(qubo.frames(spark, _Parts(spark, sf).model())[0], "b")


@query("qubo_quadratic", f"with {sql_model()}, {_LIN} select g, r, g2, r2, {r6('q')} as q from q")
def qubo_quadratic(spark, sf):
    return rounded(qubo.frames(spark, _Parts(spark, sf).model())[1], "q")


@query("qubo_scaled", f"with {sql_model()}, {_LIN}, s as (select (select sum(abs(b)) from b) + (select sum(abs(q)) from q) as s) select g, r, {r6('b / s')} as b from b, s")
def qubo_scaled(spark, sf):
    return rounded(qubo.frames(spark, qubo.normalise(_Parts(spark, sf).model()))[0], "b")


@query("qubo_penalty", f"with {sql_model()}, {_LIN} select {r6('(select sum(abs(b)) from b) + (select sum(abs(q)) from q) + 0.001')} as safe, {r6('(select sum(abs(b)) from b) + (select sum(abs(q)) from q where g <> g2 or r <> r2) + 0.001')} as off_diagonal, 1.001 + 0.0::DOUBLE as scaled")
def qubo_penalty(spark, sf):
    model = _Parts(spark, sf).model()
    row = (qubo.penalty_weight(model), qubo.penalty_bound_off_diagonal(model), qubo.penalty_weight(qubo.normalise(model)))
    return rounded(_frame(spark, [row], "safe double, off_diagonal double, scaled double"), "safe", "off_diagonal", "scaled")


_STATES3 = "s3 as materialized (select a.r as r0, b.r as r1, c3.r as r2, sum(((a.re + b.re + c3.re) / 3 - zx.re) * ((a.re + b.re + c3.re) / 3 - zx.re) + ((a.im + b.im + c3.im) / 3 - zx.im) * ((a.im + b.im + c3.im) / 3 - zx.im)) as mismatch from (select * from v where g = 0) a join (select * from v where g = 1) b on a.j = b.j join (select * from v where g = 2) c3 on a.j = c3.j join zx on a.j = zx.j group by a.r, b.r, c3.r)"


@query("qubo_identity", f"with {sql_model()}, {_STATES3} select r0, r1, r2, {r6('mismatch')} as mismatch from s3")
def qubo_identity(spark, sf):
    """Joint energy plus the constant |z|^2, for all states: the mismatch that the SQL computes directly."""
    p = _Parts(spark, sf)
    z, model = p.z(), p.model()
    states = solve.digits(np.arange(D**K), model.sizes)
    y = np.array([model.bits(s.tolist()) for s in states])
    e = model.fit_energy(y) + float((np.abs(z) ** 2).sum())
    return rounded(_frame(spark, [(*map(int, s), float(v)) for s, v in zip(states, e, strict=True)], "r0 int, r1 int, r2 int, mismatch double"), "mismatch")


def _picked(costs: list[np.ndarray]):
    pick = solve.grouped_exact(costs).selection
    return [(g, r, float(c[r])) for g, (r, c) in enumerate(zip(pick, costs, strict=True))]


def _grouped(workload: str, m: int):
    d = len(POINTS[workload][1])
    sql = f"with {sql_model(K, D, m, workload)}, {sql_costs(d)} select g, r, {r6('cost')} as cost from (select *, row_number() over (partition by g order by cost, r) as rn from cost) where rn = 1"

    def run(spark, sf):
        return rounded(_frame(spark, _picked(_Parts(spark, sf, m=m, workload=workload).costs()), "g int, r int, cost double"), "cost")

    return run, sql


Q["grouped_cluster"] = _grouped("W8", M)
Q["grouped_cluster_lineitem"] = _grouped("W12", 12)


@query("ops_sql_views", Q["grouped_cluster"][1])
def ops_sql_views(spark, sf):
    """The same selection, read from the model's views."""
    p = _Parts(spark, sf)
    names = views.register(p.points, p.centroids, p.w, p.sets)
    return spark.sql(f"select g, r, round(cost, 6) + 0.0 as cost from {names['selection']}")


@query("grouped_global", f"with {sql_model()}, {_LIN}, e as (select b.g, b.r, b.b + q.q as cost from b join q on q.g = b.g and q.r = b.r and q.g2 = b.g and q.r2 = b.r) select g, r, {r6('cost')} as cost from (select *, row_number() over (partition by g order by cost, r) as rn from e) where rn = 1")
def grouped_global(spark, sf):
    return rounded(_frame(spark, _picked(qubo.global_costs(qubo.decouple(_Parts(spark, sf).model()))), "g int, r int, cost double"), "cost")


def _selection(spark, got: solve.Solution, add: float = 0.0) -> DataFrame:
    return rounded(_frame(spark, [(",".join(map(str, got.selection)), got.value + add, got.states, got.status)], "selection string, value double, states long, status string"), "value")


@query("coupled_k3d4", f"with {sql_model()}, {_STATES3} select r0 || ',' || r1 || ',' || r2 as selection, {r6('mismatch')} as value, 64::BIGINT as states, 'solved' as status from s3 order by mismatch, r0, r1, r2 limit 1")
def coupled_k3d4(spark, sf):
    p = _Parts(spark, sf)
    return _selection(spark, solve.coupled(spark, p.model()), float((np.abs(p.z()) ** 2).sum()))


_K5 = " + ".join(f"v{g}.re" for g in range(5)), " + ".join(f"v{g}.im" for g in range(5))
_S5 = f"s5 as (select {', '.join(f'v{g}.r as r{g}' for g in range(5))}, sum((({_K5[0]}) / 5 - zx.re) * (({_K5[0]}) / 5 - zx.re) + (({_K5[1]}) / 5 - zx.im) * (({_K5[1]}) / 5 - zx.im)) as mismatch from zx {' '.join(f'join (select * from v where g = {g}) v{g} on v{g}.j = zx.j' for g in range(5))} group by all)"


@query("coupled_k5d4", f"with {sql_model(5, 4, 40)}, {_S5} select {' || '.join(f'r{g}' + (chr(32) + '||' + chr(32) + chr(39) + ',' + chr(39) if g < 4 else '') for g in range(5))} as selection, {r6('mismatch')} as value, 1024::BIGINT as states, 'solved' as status from s5 order by mismatch, r0, r1, r2, r3, r4 limit 1")
def coupled_k5d4(spark, sf):
    p = _Parts(spark, sf, 5, 4, 40)
    return _selection(spark, solve.coupled(spark, p.model()), float((np.abs(p.z()) ** 2).sum()))


@query("coupled_no_solution", f"with {sql_points('W8')}, {sql_first(10, 2)} select 'no_solution' as status, pow(6, count(*))::BIGINT as states from c")
def coupled_no_solution(spark, sf):
    """Beyond the budget the joint search gives no solution, as a result: ten clusters of parts with six candidates each."""
    got = solve.coupled(spark, _Parts(spark, sf, 10, 6).model(), budget=1_000_000)
    return _frame(spark, [(got.status, got.states)], "status string, states long")


_DIST = lambda a: f"(z.z0 - {a}.v0) * (z.z0 - {a}.v0) + (z.z1 - {a}.v1) * (z.z1 - {a}.v1)"


@query("exhaustive_wcss", f"with {sql_model()}, s as (select a.r as r0, b.r as r1, c3.r as r2, sum(least({_DIST('a')}, {_DIST('b')}, {_DIST('c3')})) as value from z cross join (select * from cand where g = 0) a cross join (select * from cand where g = 1) b cross join (select * from cand where g = 2) c3 group by a.r, b.r, c3.r) select r0 || ',' || r1 || ',' || r2 as selection, {r6('value')} as value, 64::BIGINT as states, 'solved' as status from s order by value, r0, r1, r2 limit 1")
def exhaustive_wcss(spark, sf):
    p = _Parts(spark, sf)
    return _selection(spark, solve.exhaustive(p.points, p.sets))


@query("exhaustive_sketch", Q["coupled_k3d4"][1])
def exhaustive_sketch(spark, sf):
    p = _Parts(spark, sf)
    return _selection(spark, solve.exhaustive(p.points, p.sets, "sketch", p.model()), float((np.abs(p.z()) ** 2).sum()))


_BITS = f"""with {sql_model(2)}, b as materialized (select v.g, v.r, v.g * {D} + v.r as i, -1.0 * sum(v.re * zx.re + v.im * zx.im) as b from v join zx using (j) group by v.g, v.r),
q as materialized (select x.g * {D} + x.r as i, y.g * {D} + y.r as i2, sum(x.re * y.re + x.im * y.im) / 4 as q from v x join v y on x.j = y.j group by 1, 2),
s as materialized (select (select sum(abs(b)) from b) + (select sum(abs(q)) from q) as s), t as (select range as t from range(256)),
e as (select t, (select sum(b) from b where (t >> i) & 1 = 1) as l, (select sum(q) from q where (t >> i) & 1 = 1 and (t >> i2) & 1 = 1) as qq, (1 - bit_count(t & 15)) * (1 - bit_count(t & 15)) + (1 - bit_count(t >> 4)) * (1 - bit_count(t >> 4)) as bad from t)
select bad = 0 as one_hot, t as state, {r6('(coalesce(l, 0) + coalesce(qq, 0)) / s + 1.001 * bad')} as value from e, s order by (coalesce(l, 0) + coalesce(qq, 0)) / s + 1.001 * bad, t limit 1"""


@query("all_bits_penalty", _BITS)
def all_bits_penalty(spark, sf):
    """The least total energy over all 256 strings of two groups is one-hot."""
    model = qubo.normalise(_Parts(spark, sf, 2).model())
    got = solve.bits(spark, model, qubo.penalty_weight(model))
    state = int((model.bits(got.selection) << np.arange(8)).sum()) if got.selection else -1
    return rounded(_frame(spark, [(got.selection is not None, state, got.value)], "one_hot boolean, state long, value double"), "value")


_UNIT = "u as materialized (select g, r, (cost - min(cost) over (partition by g)) / (max(cost) over (partition by g) - min(cost) over (partition by g)) as c from cost)"
_CIRCUIT = f"""with {sql_model()}, {sql_costs()}, {_UNIT}, ang as (select a::INT as gi, b::INT as bi, a * {2 * math.pi!r} / 8 as gamma, b * {math.pi / 2!r} / 8 as beta from range(9) x(a), range(9) y(b)),
ph as (select u.g, gi, bi, rr.r, 2 * pi() * q.q * (rr.r - u.r) / {D} - 4 * beta * cos(2 * pi() * q.q / {D}) - gamma * u.c as p from u cross join ang cross join range({D}) q(q) cross join range({D}) rr(r)),
pr as materialized (select g, gi, bi, r::INT as r, (sum(cos(p)) * sum(cos(p)) + sum(sin(p)) * sum(sin(p))) / {D**3} as prob from ph group by g, gi, bi, r)"""


def _p1_table(spark, sf) -> list[tuple]:
    out = []
    for g, c in enumerate(_Parts(spark, sf).costs()):
        unit = (c - c.min()) / np.ptp(c)
        probs = variational.p1(unit, np.arange(9) * 2 * np.pi / 8, np.arange(9) * np.pi / 2 / 8)
        out += [(g, a, b, r, float(probs[a, b, r])) for a in range(9) for b in range(9) for r in range(D)]
    return out


@query("circuit_p1_probs", _CIRCUIT + f" select g, gi, bi, r, {r6('prob')} as prob from pr")
def circuit_p1_probs(spark, sf):
    return rounded(_frame(spark, _p1_table(spark, sf), "g int, gi int, bi int, r int, prob double"), "prob")


@query("circuit_best_angle", _CIRCUIT + ", m as (select pr.g, gi, bi, round(sum(round(prob, 9) * round(c, 9)), 6) + 0.0 as mean from pr join u on u.g = pr.g and u.r = pr.r group by pr.g, gi, bi) select g, gi, bi, mean from (select *, row_number() over (partition by g order by mean, gi, bi) as rn from m) where rn = 1")
def circuit_best_angle(spark, sf):
    """The angle search on its grid: the angles of least mean cost, ties by order."""
    out = []
    for g, c in enumerate(_Parts(spark, sf).costs()):
        a = variational.optimise(c, grid=9, refine=0)
        gi, bi = round(float(a.gammas[0]) * float(np.ptp(c)) * 8 / (2 * math.pi)), round(float(a.betas[0]) * 16 / math.pi)
        out.append((g, gi, bi, a.value))
    return rounded(_frame(spark, out, "g int, gi int, bi int, mean double"), "mean")


_SHOTS = f"""one as (select g, r, sum(prob) over (partition by g order by r) as cdf from pr where gi = 3 and bi = 2),
sh as materialized (select g, t, {sql_uniform("'shots'", '42', 'g', 't')} as x from range({K}) a(g), range(1000) b(t)),
hit as (select sh.g, sh.t, min(r) as r from sh join one on one.g = sh.g and x <= cdf group by sh.g, sh.t), n as (select g::INT as g, r, count(*) as shots from hit group by g, r),
ranked as (select n.*, cost, row_number() over (partition by g order by shots desc, r) = 1 as mode, row_number() over (partition by g order by cost, r) = 1 as best_sampled from n join cost using (g, r))"""


@query("circuit_decode", _CIRCUIT + f", {_SHOTS} select g, r, shots, mode, best_sampled from ranked")
def circuit_decode(spark, sf):
    """Shots of hashed uniforms at one pair of angles, and what two ways of decoding make of them."""
    out, gammas, betas = [], np.arange(9) * 2 * np.pi / 8, np.arange(9) * np.pi / 2 / 8
    for g, c in enumerate(_Parts(spark, sf).costs()):
        probs = variational.simulate((c - c.min()) / np.ptp(c), gammas[3:4], betas[2:3])
        counts = variational.sample_shots(probs, 1000, 42, g, hashed=True)
        mode, cheapest = (variational.decode(probs, c, how, 1000, (42, g), hashed=True) for how in ("mode", "best_sampled"))
        out += [(g, r, n, r == mode, r == cheapest) for r, n in enumerate(counts.tolist()) if n]
    return _frame(spark, out, "g int, r int, shots long, mode boolean, best_sampled boolean")


@query("relaxation_bound", f"with {sql_model()}, {_LIN}, x as (select g, g2, max(abs(q)) as m from q where g <> g2 group by g, g2) select {r6('2 * sum(m) filter (g < g2)')} as pointwise, {r6('4 * sum(m) filter (g < g2)')} as gap from x")
def relaxation_bound(spark, sf):
    b = bounds.relaxation(_Parts(spark, sf).model())
    return rounded(_frame(spark, [(b["pointwise"], b["gap"])], "pointwise double, gap double"), "pointwise", "gap")


@query("resources_grid", "select k::INT as k, d::INT as d, b::INT as b, p::INT as p, greatest(d, greatest(1, ceil(log2(b)))::INT + 1)::INT as peak_qubits, (k * d)::INT as joint_qubits, (2 * p * case when d > 2 then d else d - 1 end)::INT as mixer_gates, (2 * p * (d * (d - 1) // 2))::INT as cost_gates from unnest([3, 5, 10]) a(k), unnest([1, 2, 4, 6, 8]) c(d), (select distinct count(*) as b from lineitem group by l_suppkey) e, unnest([1, 2, 3]) f(p)")
def resources_grid(spark, sf):
    """Resources for samples as large as the suppliers' numbers of lines."""
    sizes = table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).cast("int").alias("b")).select("b").distinct()
    return resources.grid(spark, [3, 5, 10], [1, 2, 4, 6, 8], sizes, [1, 2, 3])


def sql_lloyd(steps: int, d: int, k: int, first: str = "c") -> str:
    """CTEs a1..., c1...: Lloyd steps from c (or another start, whose name they bear then)."""
    out, centres, mark = [], first, "" if first == "c" else first
    for t in range(1, steps + 1):
        out.append(sql_assign(d, f"a{mark}{t}", centres))
        out.append(f"c{mark}{t} as materialized (select c.g, {', '.join(f'coalesce(avg(a.z{i}), any_value(c.c{i})) as c{i}' for i in range(d))} from {centres} c left join a{mark}{t} a on a.g = c.g group by c.g)")
        centres = f"c{mark}{t}"
    return ", ".join(out)


def _lloyd(workload: str):
    d = len(POINTS[workload][1])
    sql = f"with {sql_points(workload)}, {sql_first(K, d)}, {sql_lloyd(3, d, K)} select g, {', '.join(f'round(c{i}, 6) + 0.0 as c{i}' for i in range(d))} from c3"

    def run(spark, sf):
        points = _prepared(spark, sf, workload)
        c, _ = lloyd.run(points, seed.initial(points, K), 3, 0.0)
        out = _frame(spark, [(g, *map(float, v)) for g, v in enumerate(c)], "g int, " + ", ".join(f"c{i} double" for i in range(d)))
        return rounded(out, *[f"c{i}" for i in range(d)])

    return run, sql


Q["lloyd_3_steps"] = _lloyd("W8")
Q["lloyd_3_steps_lineitem"] = _lloyd("W12")


@query("wcss_standardized", f"with {sql_points('W12')}, {sql_first(K, 3)}, {sql_assign(3)} select round(sum(d2), 4) as wcss from a")
def wcss_standardized(spark, sf):
    points = _prepared(spark, sf, "W12")
    c = seed.initial(points, K)
    return _frame(spark, [(round(measures.wcss(lloyd.assign(points, c), c, prefix="z"), 4),)], "wcss double")


@query("wcss_original", f"with {sql_points('W12')}, {sql_first(K, 3)}, {sql_assign(3)} select round(log10(sum({' + '.join(f'(a.x{i} - (c.c{i} * s{i} + m{i})) * (a.x{i} - (c.c{i} * s{i} + m{i}))' for i in range(3))})), 6) as log_wcss from a join c on c.g = a.g, st")
def wcss_original(spark, sf):
    points, scaler = scale.prepare(load(spark, sf, "W12"))
    return _frame(spark, [(round(math.log10(measures.original_wcss(points, seed.initial(points, K), scaler)), 6),)], "log_wcss double")


def _pipeline_sql(steps: int = 3) -> str:
    d = 2
    ordered = f"s as materialized (select (row_number() over (order by c0, c1) - 1)::INT as g, c0, c1 from c{steps})"
    base = [sql_points("W8"), sql_freq(M, d), sql_first(K, d), sql_lloyd(steps, d, K), ordered, sql_assign(d, "a", "s"), sql_cluster_sketch(d), sql_candidates(d, D, "s"), sql_features(d)]
    base.append("cost as (select v.g, v.r, sum((v.re - zg.re) * (v.re - zg.re) + (v.im - zg.im) * (v.im - zg.im)) as cost from v join zg on zg.g = v.g and zg.j = v.j group by v.g, v.r)")
    base.append("pick as (select g, r from (select *, row_number() over (partition by g order by cost, r) as rn from cost) where rn = 1)")
    base.append("f as materialized (select cand.g, v0 as c0, v1 as c1 from cand join pick on pick.g = cand.g and pick.r = cand.r)")
    base.append(sql_assign(d, "fa", "f"))
    return f"with {', '.join(base)} select f.g, round(any_value(c0 * s0 + m0), 6) as c0, round(any_value(c1 * s1 + m1), 6) as c1, count(fa.row_key) as n, round(sum(fa.d2), 4) as wcss from f left join fa on fa.g = f.g, st group by f.g"


@query("pipeline_grouped_exact", _pipeline_sql())
def pipeline_grouped_exact(spark, sf):
    """The whole run with exact sketches and exact group minima, on parts: the flagship."""
    r = cluster(load(spark, sf, "W8"), K, M, D, b=None, shots_phase=None, solver="grouped_exact", seed_iters=3, jitter=JITTER, cache=False)
    centroids = _frame(spark, [(g, *map(float, c)) for g, c in enumerate(r.centroids_original)], "g int, c0 double, c1 double")
    sizes = r.assignments.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("d2"), 4).alias("wcss"))
    return centroids.join(sizes, "g", "left").select("g", F.round("c0", 6).alias("c0"), F.round("c1", 6).alias("c1"), F.coalesce("n", F.lit(0)).alias("n"), "wcss")


def sql_run(workload: str, m: int, solver: str = "grouped_exact", rounds: int = 1, k: int = K, iters: int = 3, b: int | None = None, shared: bool = False) -> str:
    """CTEs of a whole run up to f (the centroids) and fa (the points with their cluster and distance). With b, the sketches come
    from subsamples of b rows per frequency, dealt out of the rows in hash order, or of the first b rows for all frequencies."""
    d = len(POINTS[workload][1])
    cs = ", ".join(f"c{i}" for i in range(d))
    out = [sql_points(workload), sql_freq(m, d), sql_distinct_first(k, d), sql_lloyd(iters, d, k)]
    out.append(f"e0 as materialized (select (row_number() over (order by {cs}) - 1)::INT as g, {cs} from c{iters})")
    rank = lambda by: f"row_number() over ({by} order by {_H}, row_key) - 1"
    if b is None:
        out.append(sql_sketch(d))
    elif not shared:
        out.append(f"zx as materialized (select w.j, avg(cos({sql_dot(d, 's.z')})) as re, avg(sin({sql_dot(d, 's.z')})) as im from (select *, {rank('')} as rn from z) s join w on w.j = s.rn // {b} group by w.j)")
    for t in range(rounds):
        out.append(sql_assign(d, f"at{t}", f"e{t}"))
        if b is None:
            out.append(f"zg{t} as materialized (select g, j, avg(cos({sql_dot(d, 'a.z')})) as re, avg(sin({sql_dot(d, 'a.z')})) as im from at{t} a cross join w group by g, j)")
        else:
            out.append(f"zg{t} as materialized (select s.g, w.j, avg(cos({sql_dot(d, 's.z')})) as re, avg(sin({sql_dot(d, 's.z')})) as im from (select *, {rank('partition by g')} as rn from at{t}) s join w on {f's.rn < {b}' if shared else f'w.j = s.rn // {b}'} group by s.g, w.j)")
        moved = ", ".join(f"c{i} + case when r = 0 then 0 else {JITTER * 0.7**t!r} * {sql_normal(chr(39) + 'c' + chr(39), '42', str(t), 'g', 'r', str(i))} end as v{i}" for i in range(d))
        out.append(f"cand{t} as materialized (select g, r::INT as r, {moved} from e{t}, range({D}) x(r))")
        out.append(f"v{t} as materialized (select g, r, j, cos({sql_dot(d, 'v', 'w')}) as re, sin({sql_dot(d, 'v', 'w')}) as im from cand{t} cross join w)")
        states = ", ".join(f"s{g}.r as r{g}" for g in range(k))
        least = ", ".join(f"r{g}" for g in range(k))
        if solver == "grouped_exact":
            cost = f"(select v.g, v.r, sum((v.re - q.re) * (v.re - q.re) + (v.im - q.im) * (v.im - q.im)) as cost from v{t} v join zg{t} q on q.g = v.g and q.j = v.j group by v.g, v.r)"
            out.append(f"pick{t} as materialized (select g, r from (select *, row_number() over (partition by g order by cost, r) as rn from {cost}) where rn = 1)")
        else:
            if solver == "coupled":
                part = lambda c: f"(({' + '.join(f's{g}.{c}' for g in range(k))}) / {k} - zx.{c})"
                joins = " ".join(f"join (select * from v{t} where g = {g}) s{g} on s{g}.j = zx.j" for g in range(k))
                tried = f"select {states}, sum({part('re')} * {part('re')} + {part('im')} * {part('im')}) as value from zx {joins} group by all"
            else:
                near = lambda g: " + ".join(f"(z.z{i} - s{g}.v{i}) * (z.z{i} - s{g}.v{i})" for i in range(d))
                joins = " ".join(f"cross join (select * from cand{t} where g = {g}) s{g}" for g in range(k))
                tried = f"select {states}, sum(least({', '.join(near(g) for g in range(k))})) as value from z {joins} group by all"
            out.append(f"pick{t} as materialized (select unnest(range({k}))::INT as g, unnest([{least}]) as r from (select * from ({tried}) order by value, {least} limit 1))")
        out.append(f"e{t + 1} as materialized (select cand{t}.g, {', '.join(f'v{i} as c{i}' for i in range(d))} from cand{t} join pick{t} on pick{t}.g = cand{t}.g and pick{t}.r = cand{t}.r)")
    out.append(f"f as materialized (select * from e{rounds})")
    out.append(sql_assign(d, "fa", "f"))
    return ", ".join(out)


def _run(workload: str, m: int, solver: str = "grouped_exact", rounds: int = 1, k: int = K, iters: int = 3, b: int | None = None, shared: bool = False, **more):
    return lambda spark, sf: cluster(
        load(spark, sf, workload), k, m, D, b=b, shots_phase=None, solver=solver, refine_steps=rounds - 1, accept="guard" if solver == "grouped_exact" else "raw", seed_iters=iters, jitter=JITTER, tol=-1.0,
        sampling="shared" if b is None or shared else "per_frequency", **more,
    )


def _whole_run(workload: str, m: int, **settings):
    """Per cluster of a whole run: size, summed squared distance and first coordinate, beside the SQL of the run."""
    sql = f"with {sql_run(workload, m, **settings)} select f.g, count(fa.row_key) as n, round(coalesce(sum(fa.d2), 0), 4) as wcss, round(any_value(f.c0), 6) + 0.0 as c0 from f left join fa on fa.g = f.g group by f.g"
    run = _run(workload, m, **settings)

    def measured(spark, sf):
        r = run(spark, sf)
        centroids = _frame(spark, [(g, float(c[0])) for g, c in enumerate(r.centroids)], "g int, c0 double")
        sizes = r.assignments.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("d2"), 4).alias("wcss"))
        return rounded(centroids.join(sizes, "g", "left"), "c0").select("g", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("wcss", F.lit(0.0)).alias("wcss"), "c0")

    return measured, sql


def _record(workload: str, k: int = K, **settings):
    def run(spark, sf):
        return cluster(load(spark, sf, workload), k, **settings).record(spark, workload).drop("seconds")

    return run


Q["pipeline_circuit"] = (_record("W8"), None)
Q["pipeline_circuit_refined"] = (_record("W10", refine_steps=3, accept="guard", decode="best_sampled"), None)
Q["pipeline_noisy"] = (_record("W8", noise=NOISY), None)
Q["pipeline_refined"] = _whole_run("W10", 16, rounds=3)
Q["pipeline_coupled"] = _whole_run("W7", 28, solver="coupled")
Q["pipeline_exhaustive"] = _whole_run("W7", 28, solver="exhaustive")
Q["pipeline_coupled_refined"] = _whole_run("W8", M, solver="coupled", rounds=3)
Q["pipeline_per_frequency"] = _whole_run("W8", M, b=8)
Q["pipeline_per_frequency_coupled"] = _whole_run("W8", M, b=8, solver="coupled")
for _w in POINTS:
    if _w not in ("W9", "W10"):
        Q[f"workload_{_w}"] = _whole_run(_w, 12)


def _moments(workload: str):
    d = len(POINTS[workload][1])
    rows = " union all ".join(f"select {i}::INT as i, count(*) as n, round(any_value(m{i}), 4) + 0.0 as mean, round(any_value(s{i}), 4) + 0.0 as std from z, st" for i in range(d))

    def run(spark, sf):
        s = scale.fit(load(spark, sf, workload))
        return rounded(_frame(spark, [(i, s.n, float(s.mean[i]), float(s.std[i])) for i in range(d)], "i int, n long, mean double, std double"), "mean", "std", digits=4)

    return run, f"with {sql_points(workload)} {rows}"


for _w in POINTS:
    Q[f"moments_{_w}"] = _moments(_w)


def _summary(spark, c, value, extra="") -> DataFrame:
    return _frame(spark, [(g, [float(x) for x in v], float(value), extra) for g, v in enumerate(c)], "g int, c array<double>, value double, note string")


def _plain_summary(spark, c, value, extra="") -> DataFrame:
    """Of two features, rounded."""
    return rounded(_frame(spark, [(g, float(v[0]), float(v[1]), round(float(value), 4), extra) for g, v in enumerate(c)], "g int, c0 double, c1 double, value double, note string"), "c0", "c1")


_STEPS, _STARTS = 6, 3


def _kmeans_sql() -> str:
    ctes = [sql_points("W8")]
    for r in range(_STARTS):
        ctes += [sql_distinct_first(K, 2, 42 + r, f"k{r}_"), sql_lloyd(_STEPS, 2, K, f"k{r}_"), sql_assign(2, f"l{r}", f"ck{r}_{_STEPS}")]
    runs = " union all ".join(f"select {r} as run, (select sum(d2) from l{r}) as total, g, c0, c1 from ck{r}_{_STEPS}" for r in range(_STARTS))
    return f"with {', '.join(ctes)}, runs as ({runs}) select g, round(c0, 6) + 0.0 as c0, round(c1, 6) + 0.0 as c1, round(total, 4) as value, '' as note from runs where run = (select run from runs order by total, run limit 1)"


@query("baseline_kmeans", _kmeans_sql())
def baseline_kmeans(spark, sf):
    """Best of three starts by hash, six steps each."""
    return _plain_summary(spark, *baselines.kmeans(_prepared(spark, sf, "W8"), K, _STARTS, _STEPS, init="hash", tol=0.0))


@query("baseline_compressive")
def baseline_compressive(spark, sf):
    return _summary(spark, *compressive_baseline(load(spark, sf, "W8"), K, M))


@query("baseline_compressive_weights")
def baseline_compressive_weights(spark, sf):
    return _summary(spark, *compressive_baseline(load(spark, sf, "W8"), K, M, "free"))


def _label_sql(choose: str, push, steps: int, note: str, value: str) -> str:
    """k-means whose labels come from ``choose`` (SQL of one row and centroid, largest first) and whose means are moved by ``push``."""
    ctes = [sql_points("W8"), sql_distinct_first(K, 2, 42, "n0")]
    dist = "(z0 - c0) * (z0 - c0) + (z1 - c1) * (z1 - c1)"
    for t in range(steps):
        near = f"(select *, min(d) over (partition by row_key) as least from (select z.*, n.g, c0, c1, {dist} as d from z cross join n{t} n))"
        ctes.append(f"b{t} as materialized (select * from (select *, row_number() over (partition by row_key order by {choose.format(t=t)} desc, g) as rn from {near}) where rn = 1)")
        p = push(t)
        ctes.append(f"n{t + 1} as materialized (select n.g, {', '.join(f'coalesce(avg(b.z{i}) + any_value([{chr(44).join(repr(float(x)) for x in p[:, i])}][n.g + 1]), any_value(n.c{i})) as c{i}' for i in range(2))} from n{t} n left join b{t} b on b.g = n.g group by n.g)")
    return f"with {', '.join(ctes)} select g, round(c0, 6) + 0.0 as c0, round(c1, 6) + 0.0 as c1, (select round(sum({value}), 4) from b{steps - 1}) as value, {note} as note from n{steps}"


def _noisy_sql(delta: float = 0.1, steps: int = 3) -> str:
    pick = f"case when d <= least + {delta} then {sql_uniform(chr(39) + 'nm' + chr(39), '42', '{t}', 'g', 'row_key')} else -1 end"
    return _label_sql(pick, lambda t: baselines.pushes(K, 2, delta, t), steps, "''", "least")


@query("baseline_noisy", _noisy_sql())
def baseline_noisy(spark, sf):
    """Three steps; within delta the hash decides."""
    c, history = baselines.noisy_kmeans(_prepared(spark, sf, "W8"), K, iters=3)
    return _plain_summary(spark, c, history[-1])


def _overlap_sql(steps: int = 3) -> str:
    z = "(z0 * z0 + z1 * z1 + (c0 * c0 + c1 * c1 + 1e-12))"
    chance = f"least(1.0::DOUBLE, greatest(0.0::DOUBLE, d / (2 * {z})))"
    guess = f"-(2 * {z} * ({chance} + {sql_normal(chr(39) + 'ov' + chr(39), '42', '{t}', 'g', 'row_key')} * sqrt({chance} * (1 - {chance}) / 1024)))"
    return _label_sql(guess, lambda t: np.zeros((K, 2)), steps, f"'{resources.overlap_qubits()} qubits'", "d")


@query("baseline_overlap", _overlap_sql())
def baseline_overlap(spark, sf):
    c, history = baselines.overlap_kmeans(_prepared(spark, sf, "W8"), K, iters=3)
    return _plain_summary(spark, c, history[-1], f"{resources.overlap_qubits()} qubits")


@query("baseline_qubo", f"with {sql_points('W8')}, {sql_distinct_first(K, 2)}, {sql_lloyd(5, 2, K)} select g, round(c0, 6) + 0.0 as c0, round(c1, 6) + 0.0 as c1, (select round(sum(d2), 4) from a5) as value, 'solved' as note from c5")
def baseline_qubo(spark, sf):
    """The row's one-hot minimum is its nearest centroid, so the steps are those of k-means."""
    c, got = baselines.assign_qubo(_prepared(spark, sf, "W8"), K, 5)
    return _plain_summary(spark, c if c is not None else [], got.value or 0.0, got.status)


def _sse_sql(workload: str, m: int, **settings) -> str:
    """The SSE of a whole run in original units."""
    d = len(POINTS[workload][1])
    error = " + ".join(f"(fa.x{i} - (f.c{i} * s{i} + m{i})) * (fa.x{i} - (f.c{i} * s{i} + m{i}))" for i in range(d))
    return f"with {sql_run(workload, m, **settings)} select sum({error}) as sse from fa join f on f.g = fa.g, st"


_SWEPT = ("W7", "W8", "W12")
_TIMES = (1, 2, 4, 8)
_SIZES = (128, 256, 512, 1024)


def _at_once(jobs: list, workers: int = 4) -> list:
    """Results of independent runs; their many small jobs overlap."""
    with ThreadPoolExecutor(workers) as pool:
        return [f.result() for f in [pool.submit(job) for job in jobs]]


def _base_m(workload: str) -> int:
    return K * len(POINTS[workload][1])


def _all(parts) -> str:
    return " union all ".join(parts)


@query("sweep_frequencies", _all(f"select '{w}' as dataset, {t * _base_m(w)}::INT as m, round(log10(sse), 6) as log_sse from ({_sse_sql(w, t * _base_m(w))})" for w in _SWEPT for t in _TIMES))
def sweep_frequencies(spark, sf):
    """SSE over the number of frequencies (k d times 1, 2, 4 and 8), exact sketches and solver."""
    cells = [(w, t * _base_m(w)) for w in _SWEPT for t in _TIMES]
    got = _at_once([lambda w=w, m=m: _run(w, m)(spark, sf).sse for w, m in cells])
    return _frame(spark, [(w, m, round(math.log10(sse), 6)) for (w, m), sse in zip(cells, got, strict=True)], "dataset string, m int, log_sse double")


@query("sweep_qubits", _all(f"select '{w}' as dataset, {b}::INT as b, {resources.peak(D, b)}::INT as peak_qubits, round(log10(sse), 6) as log_sse from ({_sse_sql(w, 4 * _base_m(w), b=b, shared=True)})" for w in _SWEPT for b in _SIZES))
def sweep_qubits(spark, sf):
    """Peak qubits and SSE over the sample size, shots left out."""
    cells = [(w, b) for w in _SWEPT for b in _SIZES]
    got = _at_once([lambda w=w, b=b: _run(w, 4 * _base_m(w), b=b, shared=True)(spark, sf) for w, b in cells])
    rows = [(w, b, r.peak_qubits, round(math.log10(r.sse), 6)) for (w, b), r in zip(cells, got, strict=True)]
    return _frame(spark, rows, "dataset string, b int, peak_qubits int, log_sse double")


_SOLVERS = ("grouped_exact", "coupled", "exhaustive")
_ABLATED = [(w, k) for w in ("W7", "W8") for k in (3, 5, 10)]
_M_ABLATED = 28


def _ablation_sql() -> str:
    """Joint searches over ten groups have no solution, so they have no run."""
    def one(w: str, k: int, solver: str) -> str:
        if k == 10 and solver != "grouped_exact":
            return f"select '{w}' as dataset, {k}::INT as k, '{solver}' as solver, 'no_solution' as status, null::DOUBLE as sse"
        return f"select '{w}' as dataset, {k}::INT as k, '{solver}' as solver, 'solved' as status, sse from ({_sse_sql(w, _M_ABLATED, solver=solver, k=k)})"

    runs = _all(one(w, k, solver) for w, k in _ABLATED for solver in _SOLVERS)
    return f"with runs as materialized ({runs}) select dataset, k, solver, status, round(log10(sse), 6) as log_sse, round(sse / max(case when solver = 'grouped_exact' then sse end) over (partition by dataset, k), 6) as ratio from runs"


@query("ablation", _ablation_sql())
def ablation(spark, sf):
    """Grouped, coupled and exhaustive selection over the same candidates, SSE relative to grouped; at k = 10 the joint searches
    are beyond the budget of states. More tables are in ``experiments``."""
    cells = [(w, k, solver) for w, k in _ABLATED for solver in _SOLVERS]
    got = _at_once([lambda w=w, k=k, solver=solver: _run(w, _M_ABLATED, solver, k=k, budget=1_000_000)(spark, sf) for w, k, solver in cells])
    runs = [(*cell, r.status, r.sse if r.status == "solved" else None) for cell, r in zip(cells, got, strict=True)]
    got = measures.compare(_frame(spark, runs, "dataset string, k int, solver string, status string, sse double"), "grouped_exact")
    return got.select("dataset", "k", "solver", "status", F.round(F.log10("sse"), 6).alias("log_sse"), F.round("ratio", 6).alias("ratio"))


@query("noise_drift")
def noise_drift(spark, sf):
    ideal, noisy = (cluster(load(spark, sf, "W8"), K, noise=n, seed_iters=5).sse for n in (None, NOISY))
    return _frame(spark, [(ideal, noisy, measures.drift(ideal, noisy))], "ideal double, noisy double, drift double")


_PROJ = [" + ".join(f"z{c} * {py_normal('proj', 42, i, c) / 6**0.5!r}" for c in range(22)) for i in range(6)]


@query("random_projection", f"with {sql_points('W9')} select row_key, {', '.join(f'{r6(e)} as p{i}' for i, e in enumerate(_PROJ))} from z")
def random_projection(spark, sf):
    points = scale.project(_prepared(spark, sf, "W9"), 6)
    cols = feature_names(points, "p")
    return rounded(points.select("row_key", *cols), *cols)


_PAIRS = lambda n: f"sum({n} * ({n} - 1) / 2)"
_AGREEMENT = f"""with {sql_run('W9', 12, k=5)}, t as materialized (select g, label, count(*)::DOUBLE as n from fa join embeddings on vec_id::VARCHAR = row_key group by g, label),
a as (select g, sum(n) as n from t group by g), b as (select label, sum(n) as n from t group by label), n as (select sum(n) as n from t),
ri as (select (select {_PAIRS('n')} from t) as same, (select {_PAIRS('n')} from a) as ra, (select {_PAIRS('n')} from b) as rb, (select n * (n - 1) / 2 from n) as all_pairs),
mi as (select (select sum(t.n / n.n * ln(t.n * n.n / (a.n * b.n))) from t join a using (g) join b using (label), n) as i, (select -sum(a.n / n.n * ln(a.n / n.n)) from a, n) as ha, (select -sum(b.n / n.n * ln(b.n / n.n)) from b, n) as hb)
select round((select sum(m) from (select max(n) as m from t group by g)) / n.n, 6) as purity, round((same - ra * rb / all_pairs) / ((ra + rb) / 2 - ra * rb / all_pairs), 6) + 0.0 as ari, round(i / ((ha + hb) / 2), 6) + 0.0 as nmi from ri, mi, n"""


@query("label_agreement", _AGREEMENT)
def label_agreement(spark, sf):
    got = _run("W9", 12, k=5)(spark, sf).assignments
    e = table(spark, sf, "embeddings").select(F.col("vec_id").cast("string").alias("_k"), "label")
    a = measures.agreement(got.join(e, F.col("row_key") == F.col("_k")))
    return rounded(_frame(spark, [(a["purity"], a["ari"], a["nmi"])], "purity double, ari double, nmi double"), "purity", "ari", "nmi")


QUERIES = {n: f for n, (f, _) in Q.items()}
ORACLE_SQL = {n: s for n, (_, s) in Q.items() if s is not None}
