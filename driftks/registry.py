"""Queries by name, each with the DuckDB SQL that must give the same rows where SQL can say it.

Results of sketches vary within their guarantee, so no SQL repeats them: queries named after an approximate method return its own
numbers and have none. Two kinds of query beside them have SQL: ``approx_limit_*``, the same method at rank error zero, where every number of
it is determined, and the exact sides of the experiments. That sketches keep their bounds is for the tests.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks import streaming
from driftks.functions import significance as sig
from driftks.functions import sqlapi
from driftks.operators import cdf, drift, exact, kstest, metrics, relational, workloads
from driftks.operators.samples import Sample
from driftks.plans import params
from driftks.plans.lineage import settled, shared_folder
from driftks.sketch import direct, kll, rankbound
from driftks.sources import load

Query = Callable[[SparkSession, str], DataFrame]

# ---------------------------------------------------------------- SQL of the samples

G = "(select vec_id, generate_subscripts(embedding, 1) - 1 as dim, 8.0 * unnest(embedding)::double as z from embeddings)"
PAIRS = {
    "w1": (f"select z as value from {G} where vec_id % 2 = 0", f"select z + 1.0 as value from {G} where vec_id % 2 = 1"),
    "w2": (f"select z as value from {G} where vec_id % 2 = 0", f"select z * 1.4142135623730951::double as value from {G} where vec_id % 2 = 1"),
    "w3": (f"select z as value from {G} where vec_id % 2 = 0", f"select z as value from {G} where vec_id % 2 = 1"),
    "w4": (f"select z * z / 2.0 as value from {G}", "select (o_totalprice - 1000.0) / 499000.0 as value from orders where o_orderkey % 12 = 0"),
    "w5": (f"select z * z / 2.0 as value from {G} where vec_id % 13 <> 0", f"select z * z / 2.0 as value from {G} where vec_id % 13 = 0"),
    "price": tuple(f"select l_extendedprice as value from lineitem where l_returnflag = '{f}'" for f in "RN"),
    "quantity": tuple(f"select l_quantity as value from lineitem where l_returnflag = '{f}'" for f in "RN"),
    "discount_tax": ("select l_discount as value from lineitem", "select l_tax as value from lineitem"),
    "events_type": tuple(f"select value from events where event_type = '{k}'" for k in ("click", "purchase")),
    "events_week": ("select value from events where ts < timestamp '2024-01-22'", "select value from events where ts >= timestamp '2024-01-22' and ts < timestamp '2024-01-29'"),
    "acctbal": ("select c_acctbal as value from customer", "select s_acctbal as value from supplier"),
    "totalprice": tuple(f"select o_totalprice as value from orders where o_orderstatus = '{s}'" for s in "FO"),
    "nchars": tuple(f"select n_chars::double as value from documents join labels using (doc_id) where quality = {q}" for q in (1, 0)),
    "nchars_lang": tuple(f"select n_chars::double as value from documents where lang = '{k}'" for k in ("en", "de")),
    "textlen": tuple(f"select length(text)::double as value from conversations where role = '{r}'" for r in ("user", "assistant")),
    "retailprice": ("select p_retailprice as value from part where p_size <= 25", "select p_retailprice as value from part where p_size > 25"),
}


def tail_sql(lam: str) -> str:
    return f"(case when {lam} < 0.2 then 1.0 else greatest(0.0, least(1.0, 2.0 * (select sum((case when k % 2 = 1 then 1.0 else -1.0 end)::double * exp(-2.0::double * k * k * ({lam}) * ({lam}))) from range(1, 101) t(k)))) end)"


def gaps_sql(x: str, y: str) -> str:
    """Both functions at each distinct value."""
    return f"""s as (select value, 1 as cx, 0 as cy from ({x}) union all select value, 0, 1 from ({y})),
h as (select value, sum(cx)::bigint as cx, sum(cy)::bigint as cy from s where value is not null and not isnan(value) group by value),
t as (select sum(cx)::bigint as n, sum(cy)::bigint as m from h),
c as (select value, cx, cy, n, m, (sum(cx) over (order by value))::double / n as fx, (sum(cy) over (order by value))::double / m as fy from h, t)"""


def exact_sql(x: str, y: str, tail: str = "select round(d, 9) as d, n, m from e") -> str:
    return f"with {gaps_sql(x, y)}, e as (select max(abs(fx - fy)) as d, max(n) as n, max(m) as m from c) {tail}"


def tested_sql(x: str, y: str, alpha: float = 0.05) -> str:
    p = tail_sql("(sqrt(n::double * m / (n + m)) * d)")
    return exact_sql(x, y, f"select round(d, 9) as d, n, m, round(p, 6) as p_value, p <= {alpha} as reject from (select d, n, m, {p} as p from e)")


def certified_sql(x: str, y: str, flags: str = "true as inside") -> str:
    return exact_sql(x, y, f"select round(d, 9) as d_exact, n, m, {flags} from e")


def knots_sql(name: str, rows: str, a: int) -> str:
    """Knots ``k_{name}`` of the method at rank error zero: the value of rank ceil(p n) for each p of the grid, equal values as one jump."""
    return f"""r_{name} as (select value, row_number() over (order by value) as rn, count(*) over () as n from ({rows}) where value is not null and not isnan(value)),
g_{name} as (select n, case when i = a - 1 then 1.0::double else 1.0::double / n + (1.0::double - 1.0::double / n) * i / (a - 1) end as p
  from (select max(n) as n, least({a}, max(n)) as a from r_{name}), range({a}) t(i) where i < a),
q_{name} as (select value as x, min(p) as lo, max(p) as hi, max(g.n) as n from g_{name} g join r_{name} r on r.rn = ceil(p * g.n)::bigint group by value),
k_{name} as (select x, lo, hi, n, lead(x) over (order by x) as nx, lead(lo) over (order by x) as nlo, first_value(lo) over (order by x) as least from q_{name})"""


def limit_sql(x: str, y: str, a: int, interp: str = "linear") -> str:
    """The approximate test at rank error zero with ``a`` knots a side."""
    part = {"linear": "(v - x) / (nx - x)", "step_low": "0.0", "step_high": "1.0", "mid": "0.5"}[interp]

    def at(name: str) -> str:
        low = f"(select max(least) from k_{name})"
        return f"""f_{name} as (select v,
  max(case when x <= v and (nx is null or v < nx) then case when x = v or nx is null then hi else hi + {part} * (nlo - hi) end end) as f,
  max(case when x < v and (nx is null or v <= nx) then case when nx is null then hi else hi + {part} * (nlo - hi) end end) as l
  from pts left join k_{name} on x <= v group by v),
e_{name} as (select v, coalesce(f, {low}) as f, coalesce(l, {low}) as l from f_{name})"""

    p = tail_sql("(sqrt(n::double * m / (n + m)) * d)")
    return f"""with {knots_sql("x", x, a)}, {knots_sql("y", y, a)},
pts as (select x as v from k_x union select x from k_y),
{at("x")}, {at("y")},
d as (select max(greatest(abs(e_x.f - e_y.f), abs(e_x.l - e_y.l))) as d, (select max(n) from k_x) as n, (select max(n) from k_y) as m,
  (select count(*) from k_x) as points_x, (select count(*) from k_y) as points_y from e_x join e_y on e_x.v = e_y.v)
select n, m, points_x, points_y, round(d, 9) as d_hat, round({p}, 6) as p_value from d"""


def drawn_sql(stream: str) -> str:
    return f"((('0x' || substr(md5('{stream}:' || id), 1, 13))::bigint + 0.5) / 4503599627370496.0::double)"


def full_size_sql(name: str, reps: int, sizes: tuple[int, int], stream: str = "") -> str:
    """The rows of ``workloads.full_size``, as ``k`` (the replication), ``is_x`` and ``value``."""
    n, m = sizes
    z = f"(sqrt(-2.0::double * ln({drawn_sql(stream + name + 'a')})) * cos(6.283185307179586::double * {drawn_sql(stream + name + 'b')}))"
    x = f"{z} * {z} / 2.0" if name in ("w4", "w5") else z
    y = {"w1": f"{z} + 1.0", "w2": f"{z} * 1.4142135623730951::double", "w3": z, "w4": drawn_sql(stream + name + "a"), "w5": f"{z} * {z} / 2.0"}[name]
    return f"select (id // {n + m})::int as k, id % {n + m} < {n} as is_x, case when id % {n + m} < {n} then {x} else {y} end as value from range({reps * (n + m)}) t(id)"


def resampled_sql(name: str, reps: int, sizes: tuple[int, int], stream: str = "") -> str:
    """The rows of ``workloads.resampled``, as ``k`` (the replication), ``is_x`` and ``value``."""
    n, m = sizes
    normal = f"(select z, row_number() over (order by vec_id, dim) - 1 as no from {G} where z is not null)"
    prices = "(select (o_totalprice - 1000.0) / 499000.0 as price, row_number() over (order by o_orderkey) - 1 as no from orders where o_totalprice is not null)"

    def picked(table: str, value: str, which: str = "true") -> str:
        draws = f"(select id, id % {n + m} < {n} as is_x, floor({drawn_sql(stream + name + 'a')} * c)::bigint as pick from range({reps * (n + m)}) t(id), (select count(*) as c from {table}) where {which})"
        return f"select (id // {n + m})::int as k, is_x, {value} as value from {draws} join {table} on no = pick"

    if name == "w4":
        return f"{picked(normal, 'z * z / 2.0', f'id % {n + m} < {n}')} union all {picked(prices, 'price', f'id % {n + m} >= {n}')}"
    x, y = {"w1": ("z", "z + 1.0"), "w2": ("z", "z * 1.4142135623730951::double"), "w3": ("z", "z"), "w5": ("z * z / 2.0", "z * z / 2.0")}[name]
    return picked(normal, f"case when is_x then {x} else {y} end")


# ---------------------------------------------------------------- building blocks of queries


def exact_query(name: str, method: str = "range", alpha: float = 0.05) -> Query:
    def run(spark, sf_dir):
        out = kstest.exact_test(*workloads.pair(name, spark, sf_dir), alpha, method)
        return out.select(F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"), "reject")

    return run


def certified(d_exact: float, n: int, m: int, spark: SparkSession, **flags: bool) -> DataFrame:
    names = list(flags)
    row = spark.createDataFrame([(d_exact, n, m, *flags.values())], "d double, n long, m long" + "".join(f", {k} boolean" for k in names))
    return row.select(F.round("d", 9).alias("d_exact"), "n", "m", *names)


LIMIT = 201


def approx_query(name: str, phi: float = 0.01, **options) -> Query:
    """The approximate test: sizes, plan, stored distance with its bound, p-value with its interval, decisions."""

    def run(spark, sf_dir):
        return kstest.two_sample_test(*workloads.pair(name, spark, sf_dir), phi=phi, **options)

    return run


def limit_query(name: str, interp: str = "linear") -> Query:
    """The approximate test at rank error zero, with ``LIMIT`` knots a side: construction, ties, interpolation and distance without a sketch's noise."""

    def run(spark, sf_dir):
        pair = workloads.pair(name, spark, sf_dir)
        seen = [s.values().count() for s in pair]
        plan = params.TestPlan(0.0, *(params.plan_cdf(n, 0.0, "fixed", 0.0, LIMIT) for n in seen))
        a, b = kstest.build_pair(*pair, plan, engine="exact", interp=interp)
        d, _ = cdf.distance_py(a, b)
        row = spark.createDataFrame([(*seen, a.size, b.size, d)], "n long, m long, points_x long, points_y long, d double")
        return row.select("n", "m", "points_x", "points_y", F.round("d", 9).alias("d_hat"), F.round(sig.p_value("d", "n", "m"), 6).alias("p_value"))

    return run


def plain_routine(spark, sf_dir):
    """The routine as it is listed: plain interpolation, grid from 1/N, own knots at their own probabilities; on a pair almost without ties."""
    return kstest.two_sample_test(*workloads.pair("w3", spark, sf_dir), phi=0.01, ties="interp")


def direct_query(name: str, phi: float) -> Query:
    def run(spark, sf_dir):
        return direct.direct_sketch_test(*workloads.pair(name, spark, sf_dir), phi)

    return run


def compare_query(name: str) -> Query:
    """The comparison with the direct-sketch test at its sizes: exact distance, both approximate ones, stored points of both."""

    def run(spark, sf_dir):
        size = workloads.THIRD[name]
        rows = settled(workloads.resampled(name, spark, sf_dir, 1, (size, size), "third"))
        return metrics.compare_tests(*workloads.sides(rows), workloads.PRECISION[name])

    return run


def third_table_exact(spark, sf_dir):
    """What is determined in that comparison: exact distances, and rank errors and knots from the target precisions."""
    every, plans = None, []
    for name, size in workloads.THIRD.items():
        rows = workloads.full_size(name, spark, 1, (size, size), "third").select(F.lit(name).alias("workload"), "is_x", "value")
        every = rows if every is None else every.unionByName(rows)
        plan = params.plan_cdf(size, workloads.PRECISION[name] / 2)
        plans.append((name, plan.delta, plan.eps, plan.a, params.direct_sketch_eps(workloads.PRECISION[name])))
    out = drift.drift_by_group(every, ["workload"], F.col("value"), F.col("is_x"))
    named = spark.createDataFrame(plans, "workload string, delta double, eps double, a long, eps_sketch double")
    return out.join(F.broadcast(named), "workload").select("workload", "n", "m", F.round("d", 9).alias("d"), F.round("delta", 9).alias("delta"), F.round("eps", 9).alias("eps"), "a", F.round("eps_sketch", 9).alias("eps_sketch"))


def third_table_sql() -> str:
    rows = " union all ".join(f"select '{w}' as k, is_x, value from ({full_size_sql(w, 1, (n, n), 'third')})" for w, n in workloads.THIRD.items())
    plans = _values([(w, n, workloads.PRECISION[w] / 2) for w, n in workloads.THIRD.items()])
    hist = f"h as (select k, value, count(*) filter (where is_x) as cx, count(*) filter (where not is_x) as cy from ({rows}) group by all)"
    return grouped_sql(hist, f"""select k as workload, p.n, m, round(d, 9) as d, round(delta::double, 9) as delta, round(delta::double - sqrt(delta::double / t.n), 9) as eps, ceil(1.0 / sqrt(delta::double / t.n) + 1 - 1e-9)::bigint as a, round(delta::double / 3, 9) as eps_sketch from p join (values {plans}) t(w, n, delta) on k = w""")


def replication_query(name: str) -> Query:
    """Twenty disjoint parts of a workload at its own level and precision: ranges of distances and p-values, worst error, rejections, disagreements."""

    def run(spark, sf_dir):
        alpha, phi = workloads.SETTINGS[name]
        return metrics.replication_summary(metrics.replicate(workloads.replications(name, spark, sf_dir), phi, alpha))

    return run


def replication_exact(name: str) -> Query:
    """The exact side of the same."""

    def run(spark, sf_dir):
        alpha = workloads.SETTINGS[name][0]
        tests = drift.drift_by_group(workloads.replications(name, spark, sf_dir), ["rep"], F.col("value"), F.col("is_x")).where("d is not null")
        return tests.agg(F.round(F.min("d"), 9).alias("d_min"), F.round(F.max("d"), 9).alias("d_max"), F.count("*").alias("replications"), F.count_if(F.col("p_value") <= alpha).alias("rejected"))

    return run


def replication_sql(name: str) -> str:
    alpha = workloads.SETTINGS[name][0]
    part = lambda q: q.replace(f"from {G}", f"from (select *, (vec_id // 2) % 20 as part from {G})").replace("select ", "select part, ", 1) if G in q else q.replace("select ", "select unnest(range(20)) as part, ", 1)
    x, y = (part(q) for q in PAIRS[name])
    p = tail_sql("(sqrt(n::double * m / (n + m)) * d)")
    return f"""with s as (select part, value, 1 as cx, 0 as cy from ({x}) union all select part, value, 0, 1 from ({y})),
h as (select part, value, sum(cx) as cx, sum(cy) as cy from s group by part, value),
c as (select part, sum(cx) over w as ax, sum(cy) over w as ay, sum(cx) over (partition by part) as n, sum(cy) over (partition by part) as m from h window w as (partition by part order by value)),
d as (select part, max(n)::bigint as n, max(m)::bigint as m, max(abs(ax::double / n - ay::double / m)) as d from c where n > 0 and m > 0 group by part),
p as (select d, {p} as p from d)
select round(min(d), 9) as d_min, round(max(d), 9) as d_max, count(*) as replications, count(*) filter (where p <= {alpha}) as rejected from p"""


def full_size(name: str) -> Query:
    """The experiment at its sizes, twenty replications drawn from the given tables: each with both distances, p-values and decisions."""

    def run(spark, sf_dir):
        alpha, phi = workloads.SETTINGS[name]
        return metrics.replicate(settled(workloads.resampled(name, spark, sf_dir)), phi, alpha)

    return run


def full_size_exact(name: str) -> Query:
    """The exact test of each of the twenty replications."""

    def run(spark, sf_dir):
        out = drift.drift_by_group(workloads.resampled(name, spark, sf_dir), ["rep"], F.col("value"), F.col("is_x"))
        return out.select("rep", "n", "m", F.round("d", 9).alias("d"), F.round("p_value", 6).alias("p_value"), (F.col("p_value") <= workloads.SETTINGS[name][0]).alias("reject"))

    return run


def full_size_exact_sql(name: str) -> str:
    hist = f"h as (select k, value, count(*) filter (where is_x) as cx, count(*) filter (where not is_x) as cy from ({resampled_sql(name, 20, workloads.SIZES[name])}) group by all)"
    return grouped_sql(hist, f"select k as rep, n, m, round(d, 9) as d, round(p, 6) as p_value, p <= {workloads.SETTINGS[name][0]} as reject from p")


LAMBDAS = [0.1, 0.3, 0.5, 0.8, 1.0, 1.2, 1.36, 1.63, 2.0, 3.0]
LEVELS = [(0.05, 10_000, 10_000), (0.2, 84_000, 7_000), (0.01, 1_000, 50), (0.1, 1_107_796, 984_000)]
PARAMS = [(0.001, 1_107_796), (0.001, 984_000), (0.025, 10_000), (0.005, 10_000), (0.0005, 100_000), (0.025, 84_000), (0.001, 84_000), (0.0001995, 10_000), (0.000385, 84_000), (0.000385, 7_000)]


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(map(repr, r)) + ")" for r in rows)


def ks_tail_grid(spark, sf_dir):
    return spark.createDataFrame([(x,) for x in LAMBDAS], "lam double").select("lam", F.round(sig.ks_tail("lam"), 9).alias("tail"))


def sql_functions(spark, sf_dir):
    """The same through the SQL functions, with the probability grid from a table function."""
    sqlapi.register(spark)
    spark.createDataFrame([(x,) for x in LAMBDAS], "lam double").createOrReplaceTempView("driftks_lambdas")
    return spark.sql("select lam, round(ks_tail(lam), 9) as tail, round(ks_p_value(lam / 100, 10000D, 10000D), 9) as p, round(unit_slope_eps(0.001D, 1107796D), 9) as eps from driftks_lambdas")


def p_value_table(spark, sf_dir):
    rows = [(d, n, m) for d in (0.005, 0.0192, 0.05, 0.2) for _, n, m in LEVELS]
    return spark.createDataFrame(rows, "d double, n long, m long").select("d", "n", "m", F.round(sig.p_value("d", "n", "m"), 9).alias("p_value"))


CRITICAL = [0.01, 0.05, 0.1, 0.2]


def critical_distance_table(spark, sf_dir):
    """Critical distances between the prices of any two return flags, by level: sizes are those of the table."""
    t = load(spark, sf_dir, "lineitem").where(F.col("l_extendedprice").isNotNull() & ~F.isnan("l_extendedprice") & F.col("l_returnflag").isNotNull())
    sizes = settled(t.groupBy("l_returnflag").agg(F.count("*").alias("n")))  # a row a flag
    met = sizes.select(F.col("l_returnflag").alias("flag_x"), "n").join(sizes.select(F.col("l_returnflag").alias("flag_y"), F.col("n").alias("m")), F.col("flag_x") < F.col("flag_y"))
    each = F.explode(F.array(*(F.struct(F.lit(a).alias("alpha"), F.round(sig.critical_distance(a, F.col("n"), F.col("m")), 9).alias("d_crit")) for a in CRITICAL))).alias("c")
    return met.select("flag_x", "flag_y", "n", "m", each).select("c.alpha", "flag_x", "flag_y", "n", "m", "c.d_crit")


#: Sizes from the table, and the inverse of the tail at each level by bisection.
CRITICAL_SQL = f"""with recursive s as (select l_returnflag as flag, count(*) as n from lineitem where l_extendedprice is not null and not isnan(l_extendedprice) and l_returnflag is not null group by 1),
b(alpha, lo, hi, i) as (
  select unnest({CRITICAL})::double, 0.2::double, 10.0::double, 0
  union all
  select alpha, case when {tail_sql("((lo + hi) / 2)")} > alpha then (lo + hi) / 2 else lo end, case when {tail_sql("((lo + hi) / 2)")} > alpha then hi else (lo + hi) / 2 end, i + 1 from b where i < 60)
select alpha, x.flag as flag_x, y.flag as flag_y, x.n, y.n as m, round(lo / sqrt(x.n::double * y.n / (x.n + y.n)), 9) as d_crit
from s x join s y on x.flag < y.flag, b where i = 60"""


def precision_table(spark, sf_dir):
    """Precision of the distance that a p-value precision of half the level asks for."""
    rows = [(a, n, m, sig.precision_for(a, a / 2, n, m)) for a, n, m in LEVELS]
    return spark.createDataFrame(rows, "alpha double, n long, m long, phi double").select("alpha", "n", "m", F.round("phi", 9).alias("phi"))


#: Inverse of the tail for the levels and half and three halves of them, by bisection.
INVERSE_SQL = f"""with recursive l(alpha, n, m) as (select alpha::double, n::bigint, m::bigint from (values {_values(LEVELS)}) t(alpha, n, m)),
b(alpha, n, m, level, lo, hi, i) as (
  select alpha, n, m, alpha * f, 0.2::double, 10.0::double, 0 from l, (select unnest([0.5, 1.0, 1.5])::double as f)
  union all
  select alpha, n, m, level, case when {tail_sql("((lo + hi) / 2)")} > level then (lo + hi) / 2 else lo end, case when {tail_sql("((lo + hi) / 2)")} > level then hi else (lo + hi) / 2 end, i + 1 from b where i < 60),
c as (select alpha, n, m, level / alpha as f, lo / sqrt(n::double * m / (n + m)) as d from b where i = 60)"""


def unit_slope_table(spark, sf_dir):
    rows = [(d, n, params.unit_slope_eps(d, n), params.points_for(d, params.unit_slope_eps(d, n))) for d, n in PARAMS]
    return spark.createDataFrame(rows, "delta double, n long, eps double, a long").select("delta", "n", F.round("eps", 9).alias("eps"), "a")


def points_table(spark, sf_dir):
    rows = [(d, e, params.points_for(d, e)) for d in (0.01, 0.005) for e in (0.0, 0.001, 0.0025, 0.004)]
    return spark.createDataFrame(rows, "delta double, eps double, a long")


def tradeoff_curve(spark, sf_dir):
    c = params.tradeoff_curve(spark, 0.01, 10_000, 20)
    return c.select(F.round("eps", 9).alias("eps"), F.round("a", 6).alias("a"), F.round("slope", 9).alias("slope"), "marked")


def probability_grid(spark, sf_dir):
    return params.probability_grid_df(spark, 10_000, 51).select("knot_id", F.round("p", 9).alias("p"))


def cdf_convergence(spark, sf_dir):
    """Twenty normal samples, nine settings: the worst error at all observations, next to the bound."""
    return metrics.convergence(workloads.normal_slices(spark, sf_dir), workloads.CONVERGENCE)


def fig_curve(spark, sf_dir):
    """Exact and approximate curve of one normal sample with 11 knots and rank error 0.1, and which points are knots."""
    s = Sample(workloads.normal_slices(spark, sf_dir, 1), "value")
    return metrics.cdf_compare(s, params.plan_cdf(s.values().count(), 0.0, "fixed", 0.1, 11))


def quantile_errors(spark, sf_dir):
    """Worst rank error of returned quantiles beside the guarantee."""
    s = Sample(load(spark, sf_dir, "lineitem"), "l_extendedprice")
    n, out = s.values().count(), None
    for eps in (0.05, 0.01, 0.002):
        row = metrics.rank_guarantee(s, params.plan_cdf(n, 0.0, "fixed", eps, 101)).select(F.lit(eps).alias("eps"), "knots", "worst", "inside")
        out = row if out is None else out.unionByName(row)
    return out


def quantile_guarantee(spark, sf_dir):
    """Rank errors of returned quantiles against the guarantee, continuous and tied columns."""
    t, out = load(spark, sf_dir, "lineitem"), None
    for column in ("l_extendedprice", "l_quantity"):
        s = Sample(t, column)
        n = s.values().count()
        for engine, eps in (("summary", 0.01), ("aggregate", 0.01), ("exact", 0.0)):
            plan = params.plan_cdf(n, 0.0, "fixed", eps, 101)
            row = metrics.rank_guarantee(s, plan, engine).select(F.lit(column).alias("feature"), F.lit(engine).alias("engine"), "inside")
            out = row if out is None else out.unionByName(row)
    return out


def interp_violation(spark, sf_dir):
    """Negative control: through tied quantiles, plain interpolation breaks the bound that jumps keep."""
    x, y = workloads.pair("discount_tax", spark, sf_dir)
    d, _, n, m = exact.exact_distance(x, y, "window").first()
    plain, jump = (kstest.two_sample_test(x, y, phi=0.01, ties=t).first() for t in ("interp", "jump"))
    return certified(d, n, m, spark, plain_breaks=abs(plain["d_hat"] - d) > plain["d_bound"], jump_holds=abs(jump["d_hat"] - d) <= jump["d_bound"])


def _traces(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem")
    x = Sample(t, F.when(F.col("l_orderkey") % 43 != 0, F.col("l_discount")))
    return x, Sample(t, F.when(F.col("l_orderkey") % 10 == 0, F.lit(float("nan"))).otherwise(F.col("l_tax")))


def traces(spark, sf_dir):
    """The real-data experiment: missing readings removed first (and counted), bound 0.001, repeated values."""
    return kstest.two_sample_test(*_traces(spark, sf_dir), delta=0.001)


def traces_exact(spark, sf_dir):
    out = kstest.exact_test(*_traces(spark, sf_dir))
    return out.select(F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"), "reject")


def kll_ks(spark, sf_dir):
    return kll.direct_kll_test(*workloads.pair("price", spark, sf_dir))


def adaptive_ks(spark, sf_dir):
    """Certified where the bound allows, exact where it does not: always the exact decision."""
    return kstest.adaptive_test(*workloads.pair("events_week", spark, sf_dir)).select("n", "m", "decision")


def adaptive_result(spark, sf_dir):
    """The whole row of the adaptive test, with what it took."""
    return kstest.adaptive_test(*workloads.pair("price", spark, sf_dir), phi=0.002)


def one_scan_ks(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem").where("l_returnflag in ('R', 'N')")
    return kstest.one_scan_test(t, F.col("l_extendedprice"), F.col("l_returnflag") == "R")


def sampled_ks(spark, sf_dir):
    """Ablation: the exact test of a tenth of the rows, here those with one remainder of their keys."""
    x, y = (Sample(s.df, s.column, F.expr(s.where) & ((F.col("l_orderkey") * 7 + F.col("l_linenumber")) % 10 == 3)) for s in workloads.pair("price", spark, sf_dir))
    return kstest.exact_test(x, y).select(F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"), "reject")


def histogram_ks(spark, sf_dir):
    """Ablation: gaps at the edges of an equi-width histogram only."""
    out = kstest.histogram_test(*workloads.pair("price", spark, sf_dir), bins=100)
    return out.select(F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"), "reject")


def histogram_sql(x: str, y: str, bins: int) -> str:
    both = f"(select value, 1 as s from ({x}) union all select value, 0 from ({y}))"
    put = f"select floor({bins}::double * (value - lo) / (hi - lo)) as value from {both}, (select min(value) as lo, max(value) as hi from {both}) where s = "
    return tested_sql(put + "1", put + "0")


def exact_statement(spark, sf_dir):
    """The exact test as one Spark SQL statement: histogram, running counts, widest gap, p-value; sides by the customer that an order joins."""
    sqlapi.register(spark)
    load(spark, sf_dir, "orders").createOrReplaceTempView("driftks_orders")
    load(spark, sf_dir, "customer").createOrReplaceTempView("driftks_customer")
    return spark.sql("""
        with h as (
          select floor(o_totalprice / 1000) as value, count_if(c_acctbal > 5000) as cx, count_if(c_acctbal <= 5000) as cy
          from driftks_orders join driftks_customer on c_custkey = o_custkey
          where o_totalprice is not null and not isnan(o_totalprice) group by 1
        ), t as (
          select sum(cx) as n, sum(cy) as m from h
        ), f as (
          select abs(sum(cx) over (order by value) / (select n from t) - sum(cy) over (order by value) / (select m from t)) as gap from h
        )
        select round(d, 9) as d, n, m, round(p, 6) as p_value from (
          select d, n, m, ks_p_value(d, cast(n as double), cast(m as double)) as p from (select max(gap) as d from f) cross join t)""")


STATEMENT_SQL = tested_sql(*(f"select floor(o_totalprice / 1000) as value from orders join customer on c_custkey = o_custkey where c_acctbal {s} 5000" for s in (">", "<="))).replace(", p <= 0.05 as reject", "")


def stored_reference(spark, sf_dir):
    """A reference stored once and tested against a later week, twice: the weekly monitor of a deployed model, whose repeated run replaces itself."""
    from driftks.sources import append_results, load_cdf, save_cdf

    x, y = workloads.pair("events_week", spark, sf_dir)
    folder = shared_folder(spark, "reference")
    save_cdf(cdf.build_cdf(x, params.plan_cdf(x.values().count(), 0.005, "balanced")), spark, f"{folder}/cdf", "value", "2024-01")
    ref = load_cdf(spark, f"{folder}/cdf", "value", "2024-01")
    for _ in range(2):
        append_results(kstest.against_cdf(ref, y), f"{folder}/results", "week4")
    return spark.read.parquet(f"{folder}/results")


def storage_study(spark, sf_dir):
    """Points that both kinds of summary store for normal samples of growing size: quantiles asked for, distinct knots among them, tuples of the sketch."""
    sample_of = lambda n: Sample(workloads.full_size("w3", spark, 1, (n, 0), "space"), "value")
    return metrics.storage_study(sample_of, [10_000, 40_000, 160_000, 640_000], [0.02, 0.005])


def storage_exponents(spark, sf_dir):
    """How either grows with the size: slopes of log points over log n."""
    t = storage_study(spark, sf_dir)
    a, knots, tuples = (metrics.scaling_exponent(t, points=c).withColumnRenamed("exponent", c) for c in ("a", "knots", "tuples"))
    return a.join(knots, "delta").join(tuples, "delta")


def ecdf(name: str, column: str) -> Query:
    def run(spark, sf_dir):
        return exact.exact_cdf(Sample(load(spark, sf_dir, name), column)).select("value", "c", F.round("cdf", 9).alias("cdf"))

    return run


def top_gaps(spark, sf_dir):
    t = exact.gap_table(*workloads.pair("retailprice", spark, sf_dir))
    return t.select("value", F.round("gap", 9).alias("gap")).orderBy(F.desc("gap"), "value").limit(10)


def one_sample(name: str) -> Query:
    def run(spark, sf_dir):
        if name == "uniform":
            out = kstest.one_sample_test(Sample(load(spark, sf_dir, "orders"), "o_totalprice"), "uniform", low=1000.0, high=500000.0)
        else:
            out = kstest.one_sample_test(Sample(load(spark, sf_dir, "events"), "value"), "expon", mean=50.0)
        return out.select(F.round("d", 9).alias("d"), "n", F.round("p_value", 6).alias("p_value"))

    return run


def one_sample_sql(rows: str, model: str) -> str:
    p = tail_sql("(sqrt(n::double) * d)")
    return f"""with h as (select value, count(*) as c from ({rows}) group by value),
f as (select value, (sum(c) over (order by value))::double / (select sum(c) from h) as f, c::double / (select sum(c) from h) as own from h),
e as (select max(greatest(abs(f - ({model})), abs(f - own - ({model})))) as d, (select sum(c) from h)::bigint as n from f)
select round(d, 9) as d, n, round({p}, 6) as p_value from e"""


def one_sample_normal(spark, sf_dir):
    """Own and Spark's one-sample test against the normal model agree, and the approximate one brackets them."""
    s = Sample(workloads.gauss(spark, sf_dir), "z")
    own, theirs, band = kstest.one_sample_test(s, "norm").first(), kstest.spark_one_sample_test(s).first(), kstest.approx_one_sample_test(s, "norm").first()
    row = (own["n"], abs(own["d"] - theirs["d"]) < 1e-6, band["d_low"] <= own["d"] <= band["d_high"])
    return spark.createDataFrame([row], "n long, same boolean, bracketed boolean")


def rank_sketch_query(spark, sf_dir):
    """The rank-bound summary: every stored value's true rank lies in its bounds, and the summary is small."""
    s = Sample(load(spark, sf_dir, "lineitem"), "l_extendedprice")
    eps, ranks = 0.01, exact.exact_cdf(s).drop("n")
    b = rankbound.bounds(rankbound.rank_sketch(s, eps))
    met = b.join(ranks, b["v"] == ranks["value"]).withColumn("most", F.round(F.col("cdf") * F.col("n"))).withColumn("least", F.col("most") - F.col("c") + 1)
    out = met.agg(F.max("n").alias("n"), F.bool_and((F.col("low") <= F.col("most")) & (F.col("high") >= F.col("least"))).alias("bounded"), F.bool_and(F.col("high") - F.col("low") <= 2 * eps * F.col("n") + 2).alias("tight"), (F.count("*") <= 4 / eps).alias("small"))
    return out.select("n", "bounded", "tight", "small")


def drift_by_feature(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem").where("l_returnflag in ('R', 'N')")
    out = drift.drift_by_feature(t, ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], F.col("l_returnflag") == "R")
    return out.select("feature", F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"))


FEATURE_HIST = """u as (unpivot (select l_returnflag, l_quantity, l_extendedprice, l_discount, l_tax from lineitem where l_returnflag in ('R', 'N')) on l_quantity, l_extendedprice, l_discount, l_tax into name feature value value),
h as (select feature as k, value, count(*) filter (where l_returnflag = 'R') as cx, count(*) filter (where l_returnflag = 'N') as cy from u group by all)"""


def grouped_sql(hist: str, select: str) -> str:
    p = tail_sql("(sqrt(n::double * m / (n + m)) * d)")
    return f"""with {hist},
c as (select k, sum(cx) over w as ax, sum(cy) over w as ay, sum(cx) over (partition by k) as n, sum(cy) over (partition by k) as m from h window w as (partition by k order by value)),
d as (select k, max(n)::bigint as n, max(m)::bigint as m, max(case when n > 0 and m > 0 then abs(ax::double / n - ay::double / m) end) as d from c group by k),
p as (select k, d, n, m, {p} as p from d)
{select}"""


def holm_adjusted(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem").where("l_returnflag in ('R', 'N')")
    tests = drift.drift_by_feature(t, ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], F.col("l_returnflag") == "R").withColumn("p_value", F.round("p_value", 6))
    out = None
    for m in ("bonferroni", "holm", "bh"):
        part = drift.adjusted(tests, m).select(F.lit(m).alias("method"), "feature", F.round("p_adjusted", 5).alias("p_adjusted"))
        out = part if out is None else out.unionByName(part)
    return out


HOLM_SQL = grouped_sql(
    FEATURE_HIST,
    """, r as (select k as feature, round(p, 6) as p, row_number() over (order by p) as i, count(*) over () as n from p)
select 'bonferroni' as method, feature, round(least(1.0, p * n), 5) as p_adjusted from r
union all select 'holm', feature, round(least(1.0, max(p * (n - i + 1)) over (order by i)), 5) from r
union all select 'bh', feature, round(least(1.0, min(p * n / i) over (order by i rows between current row and unbounded following)), 5) from r""",
)


def drift_by_group(spark, sf_dir):
    """Weekly test of every event type: three weeks of reference against the fourth."""
    e = load(spark, sf_dir, "events").where("ts < timestamp_ntz'2024-01-29'")
    out = drift.drift_by_group(e, ["event_type"], F.col("value"), F.col("ts") < F.lit("2024-01-22").cast("timestamp_ntz"))
    return out.select("event_type", F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"))


def product_features(spark, sf_dir):
    """The monitor of a deployed model: several features of every event type, three weeks of reference against the fourth, one scan."""
    e = load(spark, sf_dir, "events").where("ts < timestamp_ntz'2024-01-29'")
    e = e.select("event_type", "ts", "value", F.get_json_object("props", "$.k").cast("double").alias("k"), F.hour("ts").cast("double").alias("hour"))
    out = drift.drift_by_feature(e, ["value", "k", "hour"], F.col("ts") < F.lit("2024-01-22").cast("timestamp_ntz"), ["event_type"])
    return out.select(F.concat_ws("/", "event_type", "feature").alias("name"), F.round("d", 9).alias("d"), "n", "m", F.round("p_value", 6).alias("p_value"))


PRODUCTS_H = """e as (select event_type, value, json_extract_string(props, '$.k')::double as k, hour(ts)::double as hour, ts < timestamp '2024-01-22' as x from events where ts < timestamp '2024-01-29'),
l as (select event_type || '/value' as k, value, x from e union all select event_type || '/k', k, x from e union all select event_type || '/hour', hour, x from e),
h as (select k, value, count(*) filter (where x) as cx, count(*) filter (where not x) as cy from l where value is not null group by all)"""


def cdf_band(spark, sf_dir):
    """The stored reference at all event values, with the least and the greatest value it can have: is it always between them?"""
    points = load(spark, sf_dir, "events").select("value").distinct()
    band = cdf.cdf_band(cdf.eval_cdf(points, "value", relational.reference_cdf(), "f", "array"), "value", relational.reference_cdf())
    return band.agg(F.count("*").alias("n"), F.bool_and((F.col("low") <= F.col("f") + 1e-12) & (F.col("f") <= F.col("high") + 1e-12)).alias("inside"))


def group_sketches(spark, sf_dir):
    """Rank-bound summaries of many groups in one aggregate: their ranks cover all rows, and they are small."""
    o = load(spark, sf_dir, "orders")
    out = o.groupBy("o_orderstatus").agg(sqlapi.rank_sketch_agg(0.01)(F.col("o_totalprice")).alias("s"))
    covered = F.aggregate(F.sequence(F.lit(1), F.size("s") - 2, F.lit(3)), F.lit(0.0), lambda a, i: a + F.get("s", i))
    return out.select("o_orderstatus", covered.cast("long").alias("n"), (F.size("s") / 3 <= 53).alias("small"))


def weekly_drift(spark, sf_dir):
    """Each week against the one before."""
    e = load(spark, sf_dir, "events").withColumn("week", F.floor(F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")) / 7).cast("int"))
    both = e.select("week", "value", F.lit(False).alias("is_x")).unionByName(e.select((F.col("week") + 1).alias("week"), "value", F.lit(True).alias("is_x"))).where("week between 1 and 4")
    out = drift.drift_by_group(both, ["week"], F.col("value"), F.col("is_x"))
    return out.select("week", F.round("d", 9).alias("d"), "n", "m")


def sliding_drift(spark, sf_dir):
    """Each day's events against the seven days before it."""
    e = load(spark, sf_dir, "events").select("value", F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("day"))
    before = e.select(F.explode(F.sequence(F.col("day") + 1, F.col("day") + 7)).alias("day"), "value", F.lit(True).alias("is_x"))
    both = e.select("day", "value", F.lit(False).alias("is_x")).unionByName(before).where("day between 7 and 29")
    return drift.drift_by_group(both, ["day"], F.col("value"), F.col("is_x")).select("day", F.round("d", 9).alias("d"), "n", "m")


def _balances(spark, sf_dir):
    n, r = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    place = n.join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"]).select("n_nationkey", "n_name", "r_name")
    c = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k"), F.col("c_acctbal").alias("value"), F.lit(True).alias("is_x"))
    s = load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"), F.col("s_acctbal").alias("value"), F.lit(False).alias("is_x"))
    return c.unionByName(s).join(F.broadcast(place), F.col("k") == F.col("n_nationkey"))


def drift_rollup(spark, sf_dir):
    """Customer against supplier balances by region and nation, region, and overall."""
    out = drift.drift_rollup(_balances(spark, sf_dir), ["r_name", "n_name"], F.col("value"), F.col("is_x"))
    return out.where("d is not null").select("r_name", "n_name", F.round("d", 9).alias("d"), "n", "m")


def drift_cube(spark, sf_dir):
    """Returned against other prices by status and year of shipping, every combination."""
    t = load(spark, sf_dir, "lineitem").withColumn("year", F.year("l_shipdate"))
    out = drift.drift_rollup(t, ["l_linestatus", "year"], F.col("l_extendedprice"), F.col("l_returnflag") == "R", cube=True)
    return out.where("d is not null").select("l_linestatus", "year", F.round("d", 9).alias("d"), "n", "m")


def sets_sql(rows: str, sets: str, keys: list[str]) -> str:
    k = ", ".join(keys)
    same = " and ".join(f"h.{x} is not distinct from t.{x}" for x in keys)
    return f"""with r as ({rows}),
h as (select {k}, grouping({k}) as g, value, count(*) filter (where is_x) as cx, count(*) filter (where not is_x) as cy from r group by grouping sets ({sets})),
c as (select {k}, sum(cx) over w as ax, sum(cy) over w as ay, sum(cx) over (partition by g, {k}) as n, sum(cy) over (partition by g, {k}) as m from h window w as (partition by g, {k} order by value))
select {k}, round(max(abs(ax::double / n - ay::double / m)), 9) as d, max(n)::bigint as n, max(m)::bigint as m from c where n > 0 and m > 0 group by {k}""".replace(same, same)


BALANCES = "select r_name, n_name, value, is_x from (select c_nationkey as k, c_acctbal as value, true as is_x from customer union all select s_nationkey, s_acctbal, false from supplier) join nation on k = n_nationkey join region on n_regionkey = r_regionkey"


def sketch_rollup(spark, sf_dir):
    """The same hierarchy from merged KLL sketches: sizes exact, distances within the sketches' error of the exact ones."""
    b = _balances(spark, sf_dir)
    near = drift.sketch_rollup(b, ["r_name"], F.col("value"), F.col("is_x"))
    true = drift.drift_rollup(b, ["r_name"], F.col("value"), F.col("is_x"))
    met = near.alias("a").join(true.alias("b"), (F.col("a.level") == F.col("b.level")) & F.col("a.r_name").eqNullSafe(F.col("b.r_name")))
    return met.select(F.col("a.r_name").alias("r_name"), F.col("b.n").alias("n"), F.col("b.m").alias("m"), ((F.abs(F.col("a.d") - F.col("b.d")) < 0.05) & (F.col("a.n") == F.col("b.n"))).alias("near"))


def pairwise_groups(spark, sf_dir):
    """All pairs of event types, over knots: is every distance within the bound of the exact one?"""
    e = load(spark, sf_dir, "events").select("event_type", "value")
    near = drift.pairwise_groups(e, "event_type", "value")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").collect()]
    rows = [(a, b, exact.exact_distance(Sample(e, "value", F.col("event_type") == a), Sample(e, "value", F.col("event_type") == b), "window").first()["d"]) for i, a in enumerate(kinds) for b in kinds[i + 1 :]]
    true = spark.createDataFrame(rows, "a string, b string, d double")
    return near.join(F.broadcast(true), ["a", "b"]).select("a", "b", F.round("d", 9).alias("d_exact"), (F.abs(F.col("d_hat") - F.col("d")) <= 0.021).alias("inside"))


PAIRWISE_SQL = """with h as (select a.event_type as a, b.event_type as b, v.value from (select distinct event_type from events) a join (select distinct event_type from events) b on a.event_type < b.event_type join (select distinct event_type, value from events) v on v.event_type in (a.event_type, b.event_type) group by all),
c as (select event_type, value, count(*) as c from events group by all),
j as (select h.a, h.b, h.value, coalesce(x.c, 0) as cx, coalesce(y.c, 0) as cy from h left join c x on x.event_type = h.a and x.value = h.value left join c y on y.event_type = h.b and y.value = h.value),
f as (select a, b, (sum(cx) over w)::double / sum(cx) over (partition by a, b) as fx, (sum(cy) over w)::double / sum(cy) over (partition by a, b) as fy from j window w as (partition by a, b order by value))
select a, b, round(max(abs(fx - fy)), 9) as d_exact, true as inside from f group by a, b"""


def explain_gap(spark, sf_dir):
    """Segments behind the gap of order prices at their widest point (given), by priority."""
    o = load(spark, sf_dir, "orders").where("o_orderstatus in ('F', 'O')")
    out = drift.explain_gap(o, F.col("o_totalprice"), F.col("o_orderstatus") == "F", ["o_orderpriority"], 250_000.0)
    return out.select("o_orderpriority", "x_below", "y_below", F.round("contribution", 9).alias("contribution"))


def worst_features(spark, sf_dir):
    t = load(spark, sf_dir, "lineitem").where("l_returnflag in ('R', 'N')")
    return drift.worst(drift.drift_by_feature(t, ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], F.col("l_returnflag") == "R"), 2).select("feature", F.round("d", 9).alias("d"))


def without_each(spark, sf_dir):
    o = load(spark, sf_dir, "orders").where("o_orderstatus in ('F', 'O')")
    return drift.without_each(o, "o_orderpriority", F.floor(F.col("o_totalprice") / 100), F.col("o_orderstatus") == "F").select("left_out", F.round("d", 9).alias("d"), "n", "m")


def incremental(spark, sf_dir):
    """The test after the fifth week came in and the first went out, from histogram updates."""
    e = load(spark, sf_dir, "events")
    x, y = Sample(e, "value", "event_type = 'click' and ts < timestamp_ntz'2024-01-29'"), Sample(e, "value", "event_type <> 'click' and ts < timestamp_ntz'2024-01-29'")
    side = F.when(F.col("event_type") == "click", "x").otherwise("y").alias("side")
    out = exact.incremental_test(x, y, e.where("ts >= timestamp_ntz'2024-01-29'").select(side, "value"), e.where("ts < timestamp_ntz'2024-01-08'").select(side, "value"))
    return out.select(F.round("d", 9).alias("d"), "n", "m")


def small_groups(spark, sf_dir):
    """Many small groups in one aggregate: order prices of each customer nation, half against half."""
    c = load(spark, sf_dir, "customer").select("c_nationkey", "c_acctbal", "c_custkey")
    out = sqlapi.exact_by_group(c, ["c_nationkey"], "c_acctbal", F.col("c_custkey") % 2 == 0)
    return out.where(~F.isnan("d")).select("c_nationkey", F.round("d", 9).alias("d"))


def cogrouped(spark, sf_dir):
    """The same where the two sides are two tables: customers and suppliers of each nation."""
    c = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("nation"), F.col("c_acctbal").alias("balance"))
    s = load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("nation"), F.col("s_acctbal").alias("balance"))
    return sqlapi.two_sample_cogroup(c, s, ["nation"], "balance").where("d is not null").select("nation", F.round("d", 9).alias("d"), "n", "m")


def storage_scaling(spark, sf_dir):
    """Stored points over sizes: knots of the unit-slope split grow with the root of n."""
    t = metrics.storage_model(spark, [10**k for k in range(4, 10)], [0.01, 0.001])
    return metrics.scaling_exponent(t).select("delta", (F.abs(F.col("exponent") - 0.5) < 0.05).alias("root"))


# ---------------------------------------------------------------- streams


def _events(spark, sf_dir):
    from driftks.sources import event_stream

    # a pattern: a file source takes a single file only through one
    return event_stream(spark, f"{sf_dir}/events*.parquet", load(spark, sf_dir, "events").schema)


def _ran(stream: DataFrame, spark: SparkSession, mode: str = "complete") -> DataFrame:
    return streaming.run_to_folder(stream, shared_folder(spark, "stream"), mode)


def stream_weekly(spark, sf_dir):
    """Tumbling weeks of the event stream: counts equal those of a batch, and quantiles are ordered."""
    out = _ran(streaming.weekly_knots(_events(spark, sf_dir)), spark)
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("week"), "n", (F.col("knots") == F.array_sort("knots")).alias("ordered"))


def stream_weekly_drift(spark, sf_dir):
    """Each week of the stream against the week before, over their knots."""
    return streaming.window_drift(_ran(streaming.weekly_knots(_events(spark, sf_dir)), spark))


def stream_sliding(spark, sf_dir):
    out = _ran(streaming.sliding_knots(_events(spark, sf_dir), "7 days", "1 day"), spark)
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("first_day"), "n")


def stream_session(spark, sf_dir):
    out = _ran(streaming.session_knots(_events(spark, sf_dir), "1 day", "user_id"), spark)
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


def stream_kll(spark, sf_dir):
    """Daily sketches of the stream, merged by type: counts are those of the table."""
    days = _ran(streaming.daily_sketches(_events(spark, sf_dir), keys=("event_type",)), spark)
    return streaming.merge_days(days, ("event_type",)).select("event_type", F.kll_sketch_get_n_double("sketch").alias("n"))


def stream_dedup(spark, sf_dir):
    """A stream in which every event comes twice, deduplicated within the watermark."""
    twice = _events(spark, sf_dir).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    out = _ran(streaming.deduplicated(twice, "event_id", "1 day").select("event_type", "event_id"), spark, "append")
    return out.groupBy("event_type").agg(F.count("*").alias("n"))


def stream_incremental(spark, sf_dir):
    """Histograms kept as state under insertions and removals (each event of the first week comes in and goes out again): the distance equals that of a batch."""
    e = _events(spark, sf_dir).where("event_type in ('click', 'purchase')")
    signs = F.explode(F.when(F.col("ts") < F.lit("2024-01-08").cast("timestamp"), F.array(F.lit(1), F.lit(-1))).otherwise(F.array(F.lit(1))))
    rows = e.select(F.lit("value").alias("key"), F.when(F.col("event_type") == "click", "x").otherwise("y").alias("side"), "value", signs.alias("sign"))
    changes = _ran(streaming.incremental(rows), spark, "update")
    return streaming.incremental_distance(changes).select(F.round("d", 9).alias("d"), "n", "m")


def _two(spark, sf_dir):
    e = _events(spark, sf_dir)
    return _ran(streaming.two_streams(e.where("event_type = 'click'"), e.where("event_type = 'purchase'"), "7 days"), spark)


def stream_two(spark, sf_dir):
    """Clicks against purchases, two live samples by week: counts of either."""
    return _two(spark, sf_dir).agg(F.sum("n").alias("n"), F.sum("m").alias("m"))


def stream_two_distance(spark, sf_dir):
    """The distance of the two live samples in every week, from their sketches."""
    return streaming.live_distance(_two(spark, sf_dir))


def stream_monitor(spark, sf_dir):
    """Micro-batches against a stored reference: one result a batch."""
    x, _ = workloads.pair("events_week", spark, sf_dir)
    ref, folder = cdf.build_cdf(x, params.plan_cdf(x.values().count(), 0.005, "balanced")), shared_folder(spark, "monitor")
    streaming.monitor(_events(spark, sf_dir), ref, f"{folder}/out", f"{folder}/checkpoint").start().awaitTermination()
    return spark.read.parquet(f"{folder}/out")


# ---------------------------------------------------------------- the registry

EVENTS_H = "h as (select {k} as k, value, count(*) filter (where {x}) as cx, count(*) filter (where not ({x})) as cy from {t} group by all)"
EVAL_SQL = "with k(i, x, lo, hi) as (values " + ", ".join(f"({i}, {x}::double, {lo}::double, {hi}::double)" for i, (x, lo, hi) in enumerate(relational.REFERENCE)) + """), s as (select x, lo, hi, lead(x) over (order by i) as nx, lead(lo) over (order by i) as nlo from k), p as (select distinct value from events)
select value, round(case when value < (select min(x) from k) then (select lo from k where i = 0) when nx is null or value = s.x then hi else hi + (value - s.x) / (nx - s.x) * (nlo - hi) end, 9) as f,
round(case when value < (select min(x) from k) then (select lo from k where i = 0) when value = s.x then lo when nx is null then hi else hi + (value - s.x) / (nx - s.x) * (nlo - hi) end, 9) as f_left
from p left join s on value >= s.x and (nx is null or value < nx)"""


def _entries() -> dict[str, tuple[Query, str | None]]:
    out: dict[str, tuple[Query, str | None]] = {}
    for name in ("price", "quantity", "discount_tax", "events_type", "events_week", "acctbal", "totalprice", "nchars", "nchars_lang", "textlen", "retailprice"):
        out[f"exact_ks_{name}"] = exact_query(name), tested_sql(*PAIRS[name])
    for name, label in (("w1", "gauss_shift"), ("w2", "gauss_var"), ("w3", "gauss_null"), ("w4", "gamma_unif"), ("w5", "gamma_self")):
        alpha = workloads.SETTINGS[name][0]
        out[f"exact_ks_{label}"] = exact_query(name, alpha=alpha), tested_sql(*PAIRS[name], alpha)
        out[f"approx_ks_{label}"] = approx_query(name, workloads.SETTINGS[name][1], alpha=alpha), None
        out[f"approx_limit_{label}"] = limit_query(name), limit_sql(*PAIRS[name], LIMIT)
        out[f"compare_{label}"] = compare_query(name), None
        out[f"replicate_{label}"] = replication_query(name), None
        out[f"replicate_exact_{label}"] = replication_exact(name), replication_sql(name)
        out[f"full_size_{label}"] = full_size(name), None
        out[f"full_size_exact_{label}"] = full_size_exact(name), full_size_exact_sql(name)
    for method in exact.METHODS:
        out[f"exact_ks_{'histjoin' if method == 'histogram_join' else method}"] = exact_query("price", method), tested_sql(*PAIRS["price"])
    for name in ("price", "quantity", "discount_tax", "events_type", "events_week", "acctbal", "totalprice", "nchars", "textlen", "retailprice"):
        out[f"approx_ks_{name}"] = approx_query(name), None
        out[f"approx_limit_{name}"] = limit_query(name), limit_sql(*PAIRS[name], LIMIT)
    out["approx_ks_balanced"] = approx_query("price", phi=0.002, split="balanced"), None
    out["approx_ks_summary"] = approx_query("price", engine="summary"), None
    out["approx_ks_exact_quantiles"] = approx_query("price", engine="exact"), None
    for interp in cdf.INTERPOLANTS[1:]:
        out[f"approx_ks_{interp}"] = approx_query("price", interp=interp), None
        out[f"approx_limit_{interp}"] = limit_query("price", interp), limit_sql(*PAIRS["price"], LIMIT, interp)
    for name, phi in (("price", 0.01), ("quantity", 0.01), ("w1", 0.05)):
        out[f"direct_sketch_ks_{name}"] = direct_query(name, phi), None
    x, y = PAIRS["price"]
    tenth = [f"{q} and (l_orderkey * 7 + l_linenumber) % 10 = 3" for q in (x, y)]
    out |= {
        "plain_routine": (plain_routine, None),
        "third_table_exact": (third_table_exact, third_table_sql()),
        "exact_statement": (exact_statement, STATEMENT_SQL),
        "one_scan_ks": (one_scan_ks, None),
        "kll_ks": (kll_ks, None),
        "sampled_ks": (sampled_ks, tested_sql(*tenth)),
        "histogram_ks": (histogram_ks, histogram_sql(x, y, 100)),
        "adaptive_ks": (adaptive_ks, tested_sql(*PAIRS["events_week"]).replace("round(d, 9) as d, n, m, round(p, 6) as p_value, p <= 0.05 as reject", "n, m, case when p <= 0.05 then 'reject' else 'accept' end as decision")),
        "adaptive_result": (adaptive_result, None),
        "quantile_errors": (quantile_errors, None),
        "storage_study": (storage_study, None),
        "storage_exponents": (storage_exponents, None),
        "stored_reference": (stored_reference, None),
        "interp_violation": (interp_violation, certified_sql(*PAIRS["discount_tax"], "true as plain_breaks, true as jump_holds")),
        "traces": (traces, None),
        "traces_exact": (traces_exact, tested_sql("select l_discount as value from lineitem where l_orderkey % 43 <> 0", "select l_tax as value from lineitem where l_orderkey % 10 <> 0")),
        "cdf_convergence": (cdf_convergence, None),
        "fig_curve": (fig_curve, None),
        "quantile_guarantee": (quantile_guarantee, "select f as feature, e as engine, true as inside from (values ('l_extendedprice'), ('l_quantity')) a(f), (values ('summary'), ('aggregate'), ('exact')) b(e)"),
        "rank_sketch": (rank_sketch_query, "select count(*) as n, true as bounded, true as tight, true as small from lineitem"),
        "ecdf_quantity": (ecdf("lineitem", "l_quantity"), "select value, c, round((sum(c) over (order by value))::double / sum(c) over (), 9) as cdf from (select l_quantity as value, count(*) as c from lineitem group by 1)"),
        "ecdf_windowed": (ecdf("events", "value"), "select value, c, round((sum(c) over (order by value))::double / sum(c) over (), 9) as cdf from (select value, count(*) as c from events group by 1)"),
        "value_histogram": (relational.value_histogram, "select l_quantity as value, count(*) filter (where l_returnflag = 'R') as cx, count(*) filter (where l_returnflag = 'N') as cy from lineitem group by 1"),
        "top_gaps": (top_gaps, f"with {gaps_sql(*PAIRS['retailprice'])} select value, round(abs(fx - fy), 9) as gap from c order by gap desc, value limit 10"),
        "ks_tail_grid": (ks_tail_grid, f"select lam, round({tail_sql('lam')}, 9) as tail from (select unnest({LAMBDAS})::double as lam)"),
        "sql_functions": (sql_functions, f"select lam, round({tail_sql('lam')}, 9) as tail, round({tail_sql('(sqrt(5000.0::double) * lam / 100)')}, 9) as p, round(0.001::double - sqrt(0.001::double / 1107796), 9) as eps from (select unnest({LAMBDAS})::double as lam)"),
        "p_value_table": (p_value_table, f"select d, n, m, round({tail_sql('(sqrt(n::double * m / (n + m)) * d)')}, 9) as p_value from (select unnest([0.005, 0.0192, 0.05, 0.2])::double as d), (select n::bigint as n, m::bigint as m from (values {_values([r[1:] for r in LEVELS])}) t(n, m))"),
        "critical_distance_table": (critical_distance_table, CRITICAL_SQL),
        "precision_table": (precision_table, f"{INVERSE_SQL} select a.alpha, a.n, a.m, round(min(abs(a.d - b.d)), 9) as phi from c a join c b on a.alpha = b.alpha and a.n = b.n and a.m = b.m where abs(a.f - 1) < 1e-9 and abs(b.f - 1) > 1e-9 group by all"),
        "unit_slope_table": (unit_slope_table, f"select delta::double as delta, n::bigint as n, round(delta::double - sqrt(delta::double / n), 9) as eps, ceil(1.0 / sqrt(delta::double / n) + 1 - 1e-9)::bigint as a from (values {_values(PARAMS)}) t(delta, n)"),
        "points_table": (points_table, "select delta, eps, ceil(1.0 / (delta - eps) + 1 - 1e-6)::bigint as a from (select unnest([0.01, 0.005])::double as delta), (select unnest([0.0, 0.001, 0.0025, 0.004])::double as eps)"),
        "tradeoff_curve": (tradeoff_curve, "select round(eps, 9) as eps, round(1.0 / (0.01 - eps) + 1, 6) as a, round(0.000001::double / ((0.01 - eps) * (0.01 - eps)), 9) as slope, marked from (select 0.01::double * i / 20 as eps, false as marked from range(20) t(i) union all select 0.01::double - sqrt(0.01::double / 10000), true)"),
        "probability_grid": (probability_grid, "select i::int as knot_id, round(0.0001::double + 0.9999::double * i / 50, 9) as p from range(51) t(i)"),
        "one_sample_uniform": (one_sample("uniform"), one_sample_sql("select o_totalprice as value from orders", "greatest(0.0, least(1.0, (value - 1000.0) / 499000.0))")),
        "one_sample_expon": (one_sample("expon"), one_sample_sql("select value from events", "case when value <= 0 then 0.0 else 1.0 - exp(-value / 50.0) end")),
        "one_sample_normal": (one_sample_normal, f"select count(*) as n, true as same, true as bracketed from {G}"),
        "drift_by_feature": (drift_by_feature, grouped_sql(FEATURE_HIST, "select k as feature, round(d, 9) as d, n, m, round(p, 6) as p_value from p")),
        "worst_features": (worst_features, grouped_sql(FEATURE_HIST, "select k as feature, round(d, 9) as d from p order by d desc limit 2")),
        "holm_adjusted": (holm_adjusted, HOLM_SQL),
        "drift_by_group": (drift_by_group, grouped_sql(EVENTS_H.format(k="event_type", x="ts < timestamp '2024-01-22'", t="events where ts < timestamp '2024-01-29'"), "select k as event_type, round(d, 9) as d, n, m, round(p, 6) as p_value from p")),
        "product_features": (product_features, grouped_sql(PRODUCTS_H, "select k as name, round(d, 9) as d, n, m, round(p, 6) as p_value from p")),
        "cdf_band": (cdf_band, "select count(distinct value) as n, true as inside from events"),
        "group_sketches": (group_sketches, "select o_orderstatus, count(*) as n, true as small from orders group by 1"),
        "weekly_drift": (weekly_drift, grouped_sql("b as (select datediff('day', date '2024-01-01', ts::date) // 7 as w, value from events), r as (select w, value, false as is_x from b union all select w + 1, value, true from b), " + EVENTS_H.format(k="w", x="is_x", t="r where w between 1 and 4"), "select k::int as week, round(d, 9) as d, n, m from p")),
        "sliding_drift": (sliding_drift, grouped_sql("b as (select datediff('day', date '2024-01-01', ts::date) as w, value from events), r as (select w, value, false as is_x from b union all select w + i, value, true from b, range(1, 8) t(i)), " + EVENTS_H.format(k="w", x="is_x", t="r where w between 7 and 29"), "select k::int as day, round(d, 9) as d, n, m from p")),
        "drift_rollup": (drift_rollup, sets_sql(BALANCES, "(r_name, n_name, value), (r_name, value), (value)", ["r_name", "n_name"])),
        "drift_cube": (drift_cube, sets_sql("select l_linestatus, year(l_shipdate)::int as year, l_extendedprice as value, l_returnflag = 'R' as is_x from lineitem", "(l_linestatus, year, value), (l_linestatus, value), (year, value), (value)", ["l_linestatus", "year"])),
        "sketch_rollup": (sketch_rollup, f"select r_name, count(*) filter (where is_x) as n, count(*) filter (where not is_x) as m, true as near from ({BALANCES}) group by rollup (r_name)"),
        "pairwise_groups": (pairwise_groups, PAIRWISE_SQL),
        "explain_gap": (explain_gap, "select o_orderpriority, x_below, y_below, round(x_below::double / n - y_below::double / m, 9) as contribution from (select o_orderpriority, count(*) filter (where o_orderstatus = 'F' and o_totalprice <= 250000) as x_below, count(*) filter (where o_orderstatus = 'O' and o_totalprice <= 250000) as y_below from orders where o_orderstatus in ('F', 'O') group by 1), (select count(*) filter (where o_orderstatus = 'F') as n, count(*) filter (where o_orderstatus = 'O') as m from orders)"),
        "without_each": (without_each, grouped_sql("b as (select o_orderpriority, floor(o_totalprice / 100) as value, o_orderstatus = 'F' as is_x from orders where o_orderstatus in ('F', 'O')), r as (select o.o_orderpriority as w, b.value, b.is_x from b join (select distinct o_orderpriority from b) o on o.o_orderpriority <> b.o_orderpriority), " + EVENTS_H.format(k="w", x="is_x", t="r"), "select k as left_out, round(d, 9) as d, n, m from p")),
        "incremental": (incremental, exact_sql("select value from events where event_type = 'click' and ts >= timestamp '2024-01-08'", "select value from events where event_type <> 'click' and ts >= timestamp '2024-01-08'")),
        "small_groups": (small_groups, grouped_sql(EVENTS_H.format(k="c_nationkey", x="c_custkey % 2 = 0", t="(select c_nationkey, c_custkey, c_acctbal as value from customer)"), "select k as c_nationkey, round(d, 9) as d from p where d is not null")),
        "cogrouped": (cogrouped, grouped_sql(EVENTS_H.format(k="nation", x="is_x", t="(select c_nationkey as nation, c_acctbal as value, true as is_x from customer union all select s_nationkey, s_acctbal, false from supplier)"), "select k as nation, round(d, 9) as d, n, m from p where d is not null")),
        "storage_scaling": (storage_scaling, "select delta::double as delta, true as root from (values (0.01), (0.001)) t(delta)"),
        "clean_counts": (relational.clean_counts, "select event_type, count(*) filter (where event_id % 43 <> 0 and event_id % 10 <> 0) as kept, count(*) filter (where event_id % 43 = 0 or event_id % 10 = 0) as dropped from events group by 1"),
        "slices_profile": (relational.slices_profile, f"select ((vec_id // 2) % 20)::int as slice, count(*) as n, round(min(z), 6) as low, round(max(z), 6) as high, round(avg(z), 6) as mean from {G} group by 1"),
        "join_labels": (relational.join_labels, "select quality, lang, count(*) as n, round(avg(n_chars), 6) as mean_chars from documents join labels using (doc_id) group by all"),
        "histogram_outer": (relational.histogram_outer, "select coalesce(a.v, b.v) as value, coalesce(a.c, 0) as cx, coalesce(b.c, 0) as cy from (select l_discount as v, count(*) as c from lineitem group by 1) a full join (select l_tax as v, count(*) as c from lineitem group by 1) b on a.v = b.v"),
        "parameter_grid": (relational.parameter_grid, "select a::int as a, eps::double as eps, i as slice, round(1.0::double / (a - 1) + eps::double, 9) as bound from (values " + _values(workloads.CONVERGENCE) + ") t(a, eps), range(20) s(i)"),
        "interval_events": (relational.interval_events, "select datediff('day', date '2024-01-01', ts::date) // 7 as week, count(*) as n, round(avg(value), 6) as mean from events where ts >= timestamp '2024-01-01' and ts < timestamp '2024-02-05' group by 1"),
        "describe_sample": (relational.describe_sample, "select o_orderstatus, count(*) as n, round(avg(o_totalprice), 4) as mean, round(stddev_samp(o_totalprice), 4) as sd, round(quantile_cont(o_totalprice, 0.25), 4) as q1, round(median(o_totalprice), 4) as median, round(quantile_cont(o_totalprice, 0.75), 4) as q3, min(o_totalprice) as low, max(o_totalprice) as high from orders group by 1"),
        "pivot_report": (relational.pivot_report, "select year(l_shipdate)::int as year, round(avg(l_extendedprice) filter (where l_returnflag = 'A'), 4) as flag_a, round(avg(l_extendedprice) filter (where l_returnflag = 'N'), 4) as flag_n, round(avg(l_extendedprice) filter (where l_returnflag = 'R'), 4) as flag_r from lineitem group by 1"),
        "ranked_values": (relational.ranked_values, "select s_suppkey, (row_number() over w)::int as row_no, (rank() over w)::int as rank_no, (dense_rank() over w)::int as dense_no, round(percent_rank() over w, 9) as percent, round(cume_dist() over w, 9) as cume, (ntile(4) over w)::int as quarter, lag(s_suppkey) over w as before, first_value(s_suppkey) over w as first_key, nth_value(s_suppkey, 2) over w as second_key from supplier window w as (partition by s_nationkey order by s_acctbal, s_suppkey)"),
        "rolling_mean_range": (relational.rolling_mean_range, "select event_type, value, (sum(c) over w)::bigint as within, round(sum(value * c) over w, 4) as total from (select event_type, value, count(*) as c from events group by all) window w as (partition by event_type order by value range between 5 preceding and current row)"),
        "text_features": (relational.text_features, " union all ".join(f"select '{t}' as source, count(*) as n, sum(length({c}))::bigint as chars, sum(len(string_split(trim(regexp_replace({c}, '[ \\t\\n]+', ' ', 'g')), ' ')))::bigint as words from {t}" for t, c in (("documents", "text"), ("pages", "html"), ("conversations", "text")))),
        "exploded_gauss": (relational.exploded_gauss, f"select dim::int as dim, count(*) as n, round(avg(z), 6) as mean, round(stddev_samp(z), 6) as sd from {G} group by 1"),
        "union_points": (relational.union_points, "select l_discount as x from lineitem union select l_tax from lineitem"),
        "new_values_except": (relational.new_values_except, "select x, count(*) as surplus from (select l_discount as x from lineitem except all select l_tax from lineitem) group by 1"),
        "common_values_intersect": (relational.common_values_intersect, "select x, count(*) as shared from (select l_discount as x from lineitem intersect all select l_tax from lineitem) group by 1"),
        "labelled_semi": (relational.labelled_semi, "select lang, count(*) as n, sum(n_chars)::bigint as chars from documents where doc_id in (select doc_id from labels) group by 1"),
        "unlabelled_anti": (relational.unlabelled_anti, "select lang, count(*) as n, sum(n_chars)::bigint as chars from documents where doc_id not in (select doc_id from labels) group by 1"),
        "asof_eval": (relational.asof_eval, EVAL_SQL),
        "range_join_eval": (relational.range_join_eval, EVAL_SQL),
        "nested_eval": (relational.nested_eval, EVAL_SQL),
        "broadcast_eval": (relational.broadcast_eval, EVAL_SQL),
        "array_eval": (relational.array_eval, EVAL_SQL),
        "attach_reference": (relational.attach_reference, "select event_type, count(*) as n, count(*) filter (where value > r) as over from events join (values ('click', 50.0), ('purchase', 60.0), ('view', 40.0)) t(k, r) on event_type = k group by 1"),
        "json_feature": (relational.json_feature, "select event_type, count(k) as n, sum(k)::bigint as total, min(k) as low, max(k) as high from (select event_type, json_extract_string(props, '$.k')::int as k from events) group by 1"),
        "unpivot_profile": (relational.unpivot_profile, "select l_returnflag, feature, count(*) as n, min(value) as low, max(value) as high, round(avg(value), 6) as mean from (unpivot (select l_returnflag, l_quantity, l_extendedprice, l_discount, l_tax from lineitem) on l_quantity, l_extendedprice, l_discount, l_tax into name feature value value) group by all"),
        "session_features": (relational.session_features, "select user_id, count(*) as sessions, max(c) as longest from (select user_id, s, count(*) as c from (select user_id, sum(b) over (partition by user_id order by ts, event_id) as s from (select user_id, event_id, ts, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 1 day then 0 else 1 end as b from events)) group by all) group by 1"),
        "tie_rate": (relational.tie_rate, " union all ".join(f"select '{c}' as feature, count({c}) as n, count(distinct {c}) as distinct_values from lineitem" for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax"))),
        "hash_sample": (relational.hash_sample, "select count(*) as n, round(avg(o_totalprice), 6) as mean from orders where o_orderkey % 10 = 3"),
        "sorted_sample": (relational.sorted_sample, "select c_custkey, case when c_custkey % 7 <> 0 then c_acctbal end as balance from customer order by balance nulls last, c_custkey limit 20"),
        "stream_weekly_knots": (stream_weekly, "select strftime(date '2024-01-01' + (7 * (datediff('day', date '2024-01-01', ts::date) // 7))::int, '%Y-%m-%d') as week, count(*) as n, true as ordered from events group by 1"),
        "stream_sliding": (stream_sliding, "select strftime(ts::date - i::int, '%Y-%m-%d') as first_day, count(*) as n from events, range(7) t(i) group by 1"),
        "stream_session": (stream_session, None),
        "stream_kll": (stream_kll, "select event_type, count(*) as n from events group by 1"),
        "stream_dedup": (stream_dedup, "select event_type, count(*) as n from events group by 1"),
        "stream_incremental": (stream_incremental, exact_sql(*(f"{q} and ts >= timestamp '2024-01-08'" for q in PAIRS["events_type"]))),
        "stream_weekly_drift": (stream_weekly_drift, None),
        "stream_two_distance": (stream_two_distance, None),
        "stream_two": (stream_two, "select count(*) filter (where event_type = 'click') as n, count(*) filter (where event_type = 'purchase') as m from events"),
        "stream_monitor": (stream_monitor, None),
    }
    out["stream_session"] = stream_session, out["session_features"][1]
    return out


def queries() -> dict[str, Query]:
    return {name: q for name, (q, _) in _entries().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _entries().items() if sql}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The approximate two-sample test of returned against other prices."""
    return kstest.two_sample_test(*workloads.pair("price", spark, sf_dir), phi=0.01)
