"""All queries by name, and the SQL that gives the same rows in another engine."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecquant.functions import curves, expr
from vecquant.operators import baselines, codec, fit, graph, ivf, measures, pq, prep, relational, search
from vecquant.operators.fit import Search
from vecquant.plans import cost, stepsql, workloads
from vecquant.plans import sqltext as q
from vecquant.plans.workloads import embeddings, table
from vecquant.streaming import encode

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Fixed parameters of the queries that don't fit.
FIXED = {"kuma": (2.0, 3.0), "logi": (4.0, 0.05), "pwl": (5.0, 0.05), "logi2": (5.0, 0.05)}
D = 64


def _add(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def r6(c: Column | str, places: int = 6) -> Column:
    """Rounded, and no negative zero."""
    return F.round(F.col(c) if isinstance(c, str) else c, places) + F.lit(0.0)


def _e(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "embeddings")


def _long(spark: SparkSession, sf: str) -> DataFrame:
    return measures.long_form(_e(spark, sf))


# --- profile ---------------------------------------------------------------------------------

_add("vec_dims", "SELECT len(embedding) AS d, count(*) AS n FROM embeddings GROUP BY 1")(
    lambda s, sf: _e(s, sf).groupBy(F.size("embedding").alias("d")).agg(F.count("*").alias("n"))
)
_add("vec_norms", f"SELECT vec_id, {q.r6('sqrt(' + q.DOT.format(a='embedding', b='embedding') + ')')} AS norm FROM embeddings")(
    lambda s, sf: _e(s, sf).select("vec_id", r6(expr.norm(F.col("embedding"))).alias("norm"))
)
_add("value_histogram", f"WITH {q.LONG} SELECT CAST(floor(value * 20) AS BIGINT) AS bin, count(*) AS n FROM long GROUP BY 1")(
    lambda s, sf: _long(s, sf).groupBy(F.floor(F.col("value") * 20).alias("bin")).agg(F.count("*").alias("n"))
)
_add("set_mean", f"WITH {q.LONG} SELECT CAST(dim AS INTEGER) AS dim, {q.r6('avg(value)')} AS mean FROM long GROUP BY dim")(
    lambda s, sf: prep.mean_by_dimension(_e(s, sf)).select("dim", r6("mean").alias("mean"))
)
_add("mean_by_partials", f"WITH {q.LONG} SELECT CAST(dim AS INTEGER) AS dim, {q.r6('avg(value)')} AS mean FROM long GROUP BY dim")(
    lambda s, sf: s.createDataFrame([(i, v) for i, v in enumerate(prep.fit_mean(_e(s, sf)))], "dim int, mean double").select("dim", r6("mean").alias("mean"))
)
_add(
    "centered_norms",
    f"WITH {q.LONG}, mean AS (SELECT dim, avg(value) AS m FROM long GROUP BY dim) SELECT vec_id, {q.r6('sqrt(sum(pow(value - m, 2)))')} AS norm FROM long JOIN mean USING (dim) GROUP BY vec_id",
)(lambda s, sf: prep.center(_e(s, sf), prep.fit_mean(_e(s, sf))).select("vec_id", r6(expr.norm(F.col("embedding"))).alias("norm")))
_add("per_vector_bounds", f"SELECT vec_id, {q.r6('CAST(list_min(embedding) AS DOUBLE)')} AS lo, {q.r6('CAST(list_max(embedding) AS DOUBLE)')} AS hi FROM embeddings")(
    lambda s, sf: _e(s, sf).select("vec_id", r6(F.array_min("embedding").cast("double")).alias("lo"), r6(F.array_max("embedding").cast("double")).alias("hi"))
)
_add("unit_vectors", f"SELECT vec_id, {q.r6('sqrt(' + q.DOT.format(a='embedding', b='embedding') + ')', 3)} AS norm FROM embeddings")(
    lambda s, sf: prep.normalize(_e(s, sf)).select("vec_id", r6(expr.norm(F.col("embedding")), 3).alias("norm"))
)


@_add("reject_report", "SELECT reason, n FROM (VALUES ('null', 1), ('empty', 1), ('length', 1), ('not finite', 2)) t(reason, n) UNION ALL SELECT 'kept', count(*) FROM embeddings")
def reject_report(spark: SparkSession, sf: str) -> DataFrame:
    base = _e(spark, sf).select("vec_id", "embedding")
    odd = [(-1, None), (-2, []), (-3, [1.0]), (-4, [float("nan")] * D), (-5, [float("inf")] * D)]
    good, bad = prep.validate_vectors(base.unionByName(spark.createDataFrame(odd, base.schema)), D)
    return bad.groupBy("reason").agg(F.count("*").alias("n")).unionByName(good.agg(F.lit("kept").alias("reason"), F.count("*").alias("n")))


_KDE = f"""WITH {q.LONG}, own AS (SELECT * FROM long WHERE vec_id < 4),
    stats AS (SELECT vec_id, stddev_samp(value) AS sd, count(*) AS n, min(lo) AS lo, min(hi) AS hi FROM own GROUP BY vec_id),
    spots AS (SELECT vec_id, n, 1.06 * sd * pow(n, -0.2) AS h, k, lo + (hi - lo) * k / 63 AS x FROM stats, range(64) t(k))
    SELECT vec_id, CAST(k AS INTEGER) AS k, {q.r6('x')} AS x, {q.r6('sum(exp(-0.5 * pow((x - value) / h, 2)) / (n * h * sqrt(2 * pi())))')} AS density
    FROM spots JOIN own USING (vec_id) GROUP BY vec_id, k, x"""
_add("kde_four", _KDE)(lambda s, sf: workloads.density(s, sf).select("vec_id", "k", r6("x").alias("x"), r6("density").alias("density")))

# --- curves ----------------------------------------------------------------------------------

_A = [(0.5, 0.5), (1.0, 1.0), (2.0, 3.0), (5.0, 2.0)]
_B = [(1.0, 0.0), (4.0, 0.0), (8.0, 0.2)]


def _grid(spark: SparkSession, sf: str) -> DataFrame:
    return spark.range(1, 100).select((F.col("id") / 100).alias("x"))


_GRID = "(SELECT CAST(k AS DOUBLE) / 100 AS x FROM range(1, 100) t(k))"


def _places(spark: SparkSession, sf: str) -> DataFrame:
    """vec_id, dim, x: every given value's place between its vector's bounds, drawn in from the ends."""
    return _long(spark, sf).where("hi > lo").select("vec_id", "dim", (0.01 + 0.98 * ((F.col("value") - F.col("lo")) / (F.col("hi") - F.col("lo")))).alias("x"))


_PLACES = f"(WITH {q.LONG} SELECT vec_id, CAST(dim AS INTEGER) AS dim, CAST(0.01 AS DOUBLE) + CAST(0.98 AS DOUBLE) * ((value - lo) / (hi - lo)) AS x FROM long WHERE hi > lo)"


def _curve_values(pairs: list[tuple[float, float]], column: Callable, text: Callable) -> tuple[Query, str]:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        each = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), r6(column(F.col("x"), a, b)).alias("h")) for a, b in pairs])).alias("t")
        return _places(spark, sf).select("vec_id", "dim", each).select("vec_id", "dim", "t.a", "t.b", "t.h")

    sql = " UNION ALL ".join(f"SELECT vec_id, dim, {q.num(a)} AS a, {q.num(b)} AS b, {q.r6(text('x', a, b))} AS h FROM {_PLACES}" for a, b in pairs)
    return run, sql


def _curve_grid(pairs: list[tuple[float, float]], column: Callable, text: Callable, center: float = 0.0) -> tuple[Query, str]:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        x = F.col("x") - F.lit(center)
        each = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), r6(column(x, a, b)).alias("h")) for a, b in pairs])).alias("t")
        return _grid(spark, sf).select(r6("x").alias("x"), each).select("x", "t.a", "t.b", "t.h")

    sql = " UNION ALL ".join(f"SELECT {q.r6('x')} AS x, {q.num(a)} AS a, {q.num(b)} AS b, {q.r6(text(f'(x - {q.num(center)})', a, b))} AS h FROM {_GRID}" for a, b in pairs)
    return run, sql


for _name, _pairs, _column, _text in (
    ("kuma_grid", _A, expr.kumaraswamy, q.kuma),
    ("kuma_quantile_grid", _A, expr.kumaraswamy_inverse, q.kuma_inverse),
    ("kuma_pdf_grid", _A, lambda x, a, b: a * b * F.pow(x, F.lit(a - 1)) * F.pow(1 - F.pow(x, F.lit(a)), F.lit(b - 1)), lambda x, a, b: f"({a} * {b} * pow({x}, {q.num(a - 1)}) * pow(1 - pow({x}, {q.num(a)}), {q.num(b - 1)}))"),
):
    _run, _sql = _curve_values(_pairs, _column, _text)
    _add(_name, _sql)(_run)

for _name, _pairs, _column, _text, _center in (
    ("logistic_grid", _B, expr.logistic, lambda x, a, b: q.raw("logi", x, a, b), 0.5),
    ("logit_grid", _B, expr.logit, lambda x, a, b: q.raw_inverse("logi", x, a, b), 0.0),
    ("logistic2_grid", _B, expr.logistic2, lambda x, a, b: q.raw("logi2", x, a, b), 0.5),
    ("pwl_logistic_grid", _B, expr.pwl_logistic, lambda x, a, b: q.raw("pwl", x, a, b), 0.5),
    ("pwl_logit_grid", _B, expr.pwl_logit, lambda x, a, b: q.raw_inverse("pwl", x, a, b), 0.0),
    ("pwl_log2_grid", [(1.0, 0.0)], lambda x, a, b: expr.pwl_log2(x * 16), lambda x, a, b: q.pwl_log2(f"({x} * 16)"), 0.0),
):
    _run, _sql = _curve_grid(_pairs, _column, _text, _center)
    _add(_name, _sql)(_run)


def _kernel_grid(form: str, spark: SparkSession, sf: str) -> DataFrame:
    """Kumaraswamy curve and its inverse by the batch kernel in one of its forms, at the given values' places."""

    def run(batches):  # noqa: ANN001, ANN202
        for part in batches:
            x = part["x"].to_numpy()
            for a, b in _A:
                yield pd.DataFrame({"vec_id": part["vec_id"], "dim": part["dim"], "a": a, "b": b, "h": curves.kumaraswamy(x, np.float64(a), np.float64(b), form), "back": curves.kumaraswamy_inverse(x, np.float64(a), np.float64(b), form)})

    rows = _places(spark, sf).mapInPandas(run, "vec_id long, dim int, a double, b double, h double, back double")
    return rows.select("vec_id", "dim", "a", "b", r6("h").alias("h"), r6("back").alias("back"))


for _form in ("pow", "explog", "poly"):
    _add(f"kuma_kernel_{_form}", " UNION ALL ".join(f"SELECT vec_id, dim, {q.num(a)} AS a, {q.num(b)} AS b, {q.r6(q.kuma('x', a, b))} AS h, {q.r6(q.kuma_inverse('x', a, b))} AS back FROM {_PLACES}" for a, b in _A))(
        lambda s, sf, f=_form: _kernel_grid(f, s, sf)
    )
_RAW_PARAMS = [(-3.0, -2.0), (0.0, 0.0), (2.5, 0.3), (4.0, 9.0)]


@_add(
    "projected_params",
    "WITH e AS (SELECT vec_id, CAST(list_min(embedding) AS DOUBLE) AS lo, CAST(list_max(embedding) AS DOUBLE) AS hi FROM embeddings), p AS (SELECT * FROM (VALUES "
    + ", ".join(f"({q.num(a)}, {q.num(b)})" for a, b in _RAW_PARAMS)
    + f") t(a, b)) SELECT vec_id, a, b, greatest(a, {q.num(curves.FLOOR)}) AS p0, {q.r6('least(greatest(b, lo / (hi - lo)), hi / (hi - lo))')} AS p1, greatest(b, {q.num(curves.FLOOR)}) AS k1 FROM e, p",
)
def projected_params(spark: SparkSession, sf: str) -> DataFrame:
    """The nearest allowed parameters of the logistic curves (p0, p1) and of the general curve (p0, k1)."""

    def run(batches):  # noqa: ANN001, ANN202
        for part in batches:
            lo, hi = part["lo"].to_numpy(), part["hi"].to_numpy()
            for a, b in _RAW_PARAMS:
                p0, p1 = curves.project("logi", np.full(len(lo), a), np.full(len(lo), b), lo, hi)
                _, k1 = curves.project("kuma", np.full(len(lo), a), np.full(len(lo), b), lo, hi)
                yield pd.DataFrame({"vec_id": part["vec_id"], "a": a, "b": b, "p0": p0, "p1": p1, "k1": k1})

    rows = measures.bounded(_e(spark, sf)).select("vec_id", "lo", "hi").mapInPandas(run, "vec_id long, a double, b double, p0 double, p1 double, k1 double")
    return rows.withColumn("p1", r6("p1"))


def _scaled(curve: str) -> tuple[Query, str]:
    p0, p1 = FIXED[curve]

    def run(spark: SparkSession, sf: str) -> DataFrame:
        lo, hi = F.lit(-1.0), F.lit(1.0)
        rows = _grid(spark, sf).select((2 * F.col("x") - 1).alias("x"))
        h = expr.bend(curve, F.col("x"), lo, hi, p0, p1)
        rows = rows.select("x", h.alias("bent"))
        return rows.select(r6("x").alias("x"), r6("bent").alias("h"), r6(expr.unbend(curve, F.col("bent"), lo, hi, p0, p1)).alias("back"))

    sql = f"""WITH g AS (SELECT 2 * x - 1 AS x, CAST(-1 AS DOUBLE) AS lo, CAST(1 AS DOUBLE) AS hi FROM {_GRID}),
        b AS (SELECT *, {q.bend(curve, 'x', p0=p0, p1=p1)} AS h FROM g)
        SELECT {q.r6('x')} AS x, {q.r6('h')} AS h, {q.r6(q.unbend(curve, 'h', p0=p0, p1=p1))} AS back FROM b"""
    return run, sql


for _curve in ("kuma", "logi", "logi2", "pwl"):
    _run, _sql = _scaled(_curve)
    _add(f"scaled_{_curve}_roundtrip", _sql)(_run)

_add("pwl_gap", f"SELECT {q.r6('max(log2(x * 16) - ' + q.pwl_log2('(x * 16)') + ')')} AS most, {q.r6('min(log2(x * 16) - ' + q.pwl_log2('(x * 16)') + ')')} AS least FROM {_GRID}")(
    lambda s, sf: _grid(s, sf).select((F.log2(F.col("x") * 16) - expr.pwl_log2(F.col("x") * 16)).alias("g")).agg(r6(F.max("g")).alias("most"), r6(F.min("g")).alias("least"))
)
_add("base_change", f"SELECT {q.r6('max(abs(' + q.raw('logi', 'x', 3.0, 0.5) + ' - ' + q.raw('logi2', 'x', 3.0 / np.log(2), 0.5) + '))')} AS gap FROM {_PLACES}")(
    lambda s, sf: _places(s, sf).agg(r6(F.max(F.abs(expr.logistic(F.col("x"), 3.0, 0.5) - expr.logistic2(F.col("x"), 3.0 / np.log(2), 0.5)))).alias("gap"))
)
_add("raw_param_equiv", f"SELECT {q.r6('max(abs(' + q.raw('logi', '(x / 0.4)', 4.0, 0.1) + ' - ' + q.raw('logi', 'x', 4.0 / 0.4, 0.1 * 0.4) + '))')} AS gap FROM {_GRID}")(
    lambda s, sf: _grid(s, sf).agg(r6(F.max(F.abs(expr.logistic(F.col("x") / 0.4, 4.0, 0.1) - expr.logistic(F.col("x"), 4.0 / 0.4, 0.1 * 0.4)))).alias("gap"))
)

# --- codes -----------------------------------------------------------------------------------


def _codes(curve: str, bits: int, spark: SparkSession, sf: str) -> DataFrame:
    p0, p1 = FIXED.get(curve, (1.0, 1.0))
    code = expr.quantize(curve, F.col("value"), F.col("lo"), F.col("hi"), p0, p1, bits)
    return _long(spark, sf).select("vec_id", "dim", code.alias("code"))


def _codes_sql(curve: str, bits: int) -> str:
    return f"WITH {q.LONG} SELECT vec_id, CAST(dim AS INTEGER) AS dim, {q.code(curve, bits, *FIXED.get(curve, (1.0, 1.0)))} AS code FROM long"


for _curve, _bits in (("unif", 8), ("unif", 4), ("kuma", 8), ("logi", 8), ("pwl", 8), ("logi2", 8), ("logi", 4)):
    _add(f"{_curve}_codes{_bits}", _codes_sql(_curve, _bits))(lambda s, sf, c=_curve, b=_bits: _codes(c, b, s, sf))


def _loss_sql(curve: str, bits: int) -> str:
    p = FIXED.get(curve, (1.0, 1.0))
    return f"""WITH {q.LONG}, coded AS (SELECT *, {q.code(curve, bits, *p)} AS code, {q.code('unif', bits)} AS flat FROM long)
        SELECT vec_id, sum({q.error('unif', bits, coded='flat')}) AS u, sum({q.error(curve, bits, *p)}) AS l FROM coded GROUP BY vec_id"""


for _bits in (8, 4):
    _add(f"uniform_loss{_bits}", f"SELECT vec_id, {q.r6('u * 1000')} AS loss FROM ({_loss_sql('unif', _bits)})")(
        lambda s, sf, b=_bits: measures.recon_loss(_e(s, sf), "unif", bits=b).select("vec_id", r6(F.col("loss") * 1000).alias("loss"))
    )
for _curve in ("kuma", "logi", "pwl"):
    _add(f"fixed_gain_{_curve}", f"SELECT vec_id, {q.r6('u / l')} AS gain FROM ({_loss_sql(_curve, 8)})")(
        lambda s, sf, c=_curve: measures.gain(_e(s, sf), c, *FIXED[c]).select("vec_id", r6("gain").alias("gain"))
    )


@_add("kernel_equals_columns", "SELECT CAST(count(*) AS BIGINT) * 64 AS n_values, CAST(0 AS BIGINT) AS differences FROM embeddings")
def kernel_equals_columns(spark: SparkSession, sf: str) -> DataFrame:
    """Values and differences of codes by the batch kernel and by columns."""
    s = Search(curve="unif", bits=8, split="contiguous")
    kernel = codec.encode(_e(spark, sf), s).select("vec_id", F.hex("codes").alias("k"))
    columns = _e(spark, sf).select("vec_id", expr.quantize_array("unif", F.transform("embedding", lambda v: v.cast("double")), bits=8).alias("c"))
    columns = columns.select("vec_id", F.array_join(F.transform("c", lambda c: F.lpad(F.hex(c.cast("long")), 2, "0")), "").alias("c"))
    joined = columns.join(kernel, "vec_id")
    wrong = F.size(F.filter(F.sequence(F.lit(0), F.lit(D - 1)), lambda i: F.substring("k", i * 2 + 1, F.lit(2)) != F.substring("c", i * 2 + 1, F.lit(2))))
    return joined.agg((F.count("*") * D).alias("n_values"), F.sum(wrong).cast("long").alias("differences"))


_add(
    "uniform_global",
    f"""WITH {q.LONG}, ends AS (SELECT min(value) AS a, max(value) AS b FROM long), w AS (SELECT vec_id, value, a AS lo, b AS hi FROM long, ends),
    coded AS (SELECT *, {q.code('unif', 8)} AS code FROM w) SELECT vec_id, {q.r6('sum(' + q.error('unif', 8) + ') * 1000')} AS loss FROM coded GROUP BY vec_id""",
)(lambda s, sf: baselines.uniform_global(_e(s, sf)).select("vec_id", r6(F.col("loss") * 1000).alias("loss")))
_SHARES = "[" + ", ".join(f"{k}.0 / 15" for k in range(16)) + "]"
_add(
    "cdf_loss",
    f"""WITH {q.LONG}, levels AS (SELECT vec_id, list_transform({_SHARES}, lambda x: 0) AS z, quantile_cont(value, {[k / 15 for k in range(16)]}) AS lv FROM long GROUP BY vec_id)
    SELECT vec_id, {q.r6('sum(pow(list_min(list_transform(lv, lambda v: abs(value - v))), 2))')} AS loss FROM long JOIN levels USING (vec_id) GROUP BY vec_id""",
)(lambda s, sf: baselines.cdf(_e(s, sf), 4).select("vec_id", r6("loss").alias("loss")))
_add("cdf_loss8", f"""WITH {q.LONG}, levels AS (SELECT vec_id, quantile_cont(value, {[k / 255 for k in range(256)]}) AS lv FROM long GROUP BY vec_id)
    SELECT vec_id, {q.r6('sum(pow(list_min(list_transform(lv, lambda v: abs(value - v))), 2)) * 1000')} AS loss FROM long JOIN levels USING (vec_id) GROUP BY vec_id""")(
    lambda s, sf: baselines.cdf(_e(s, sf), 8).select("vec_id", r6(F.col("loss") * 1000).alias("loss"))
)
_add("cdf_codes4", f"""WITH {q.LONG}, levels AS (SELECT vec_id, quantile_cont(value, {[k / 15 for k in range(16)]}) AS lv FROM long GROUP BY vec_id),
    c AS (SELECT vec_id, list_position(list_transform(lv, lambda v: round(abs(value - v), 12)), list_min(list_transform(lv, lambda v: round(abs(value - v), 12)))) - 1 AS code FROM long JOIN levels USING (vec_id))
    SELECT vec_id, CAST(sum(code) AS BIGINT) AS code_sum FROM c GROUP BY vec_id""")(
    lambda s, sf: baselines.cdf_codes(_e(s, sf), 4).select("vec_id", F.aggregate("codes", F.lit(0).cast("long"), lambda a, c: a + c).alias("code_sum"))
)
_add("cdf_set_loss", f"""WITH {q.LONG}, levels AS (SELECT quantile_disc(value, {[k / 15 for k in range(16)]}) AS lv FROM long)
    SELECT vec_id, {q.r6('sum(pow(list_min(list_transform(lv, lambda v: abs(value - v))), 2))', 3)} AS loss FROM long, levels GROUP BY vec_id""")(
    lambda s, sf: baselines.cdf(_e(s, sf), 4, "set").select("vec_id", r6("loss", 3).alias("loss"))
)
_add(
    "lossless_bytes",
    "SELECT vec_id, CAST(4 * len(list_distinct(embedding)) + ceil(len(embedding) * ceil(log2(greatest(len(list_distinct(embedding)), 2))) / 8) AS BIGINT) AS lossless, CAST(4 * len(embedding) AS BIGINT) AS fp32 FROM embeddings",
)(lambda s, sf: baselines.lossless_bytes(_e(s, sf)))
_add("pack4_hex", f"WITH {q.LONG}, coded AS (SELECT vec_id, dim, {q.code('unif', 4)} AS code FROM long) SELECT vec_id, string_agg(lower(to_hex(code)), '' ORDER BY dim) AS packed FROM coded GROUP BY vec_id")(
    lambda s, sf: _e(s, sf).select("vec_id", codec.pack4_hex(expr.quantize_array("unif", F.transform("embedding", lambda v: v.cast("double")), bits=4)).alias("packed"))
)
_add("code_entropy", f"WITH {q.LONG}, c AS (SELECT {q.code('unif', 8)} AS code FROM long), n AS (SELECT code, count(*) AS n FROM c GROUP BY code), t AS (SELECT sum(n) AS t FROM n) SELECT {q.r6('-sum(n / t * log2(n / t))')} AS entropy FROM n, t")(
    lambda s, sf: relational.code_entropy(_codes("unif", 8, s, sf)).select(r6("entropy").alias("entropy"))
)
_add("levels_used", f"WITH {q.LONG}, c AS (SELECT vec_id, {q.code('unif', 8)} AS code FROM long) SELECT vec_id, count(DISTINCT code) AS levels FROM c GROUP BY vec_id")(
    lambda s, sf: relational.levels_used(_codes("unif", 8, s, sf)).select("vec_id", "levels")
)

# --- sub-vectors -----------------------------------------------------------------------------


def _split_sql(m: int, perm: list[int] | None = None) -> str:
    width = D // m
    order = "CAST(dim AS INTEGER)" if perm is None else f"(list_position({[int(p) for p in perm]}, CAST(dim AS INTEGER)) - 1)"
    return f"""WITH v AS (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS value, unnest(range(len(embedding))) AS dim FROM embeddings),
        parts AS (SELECT vec_id, value, {order} // {width} AS part FROM v),
        b AS (SELECT *, min(value) OVER (PARTITION BY vec_id, part) AS lo, max(value) OVER (PARTITION BY vec_id, part) AS hi FROM parts),
        coded AS (SELECT *, {q.code('unif', 4)} AS code FROM b)
        SELECT vec_id, {q.r6('sum(' + q.error('unif', 4) + ')')} AS loss FROM coded GROUP BY vec_id"""


for _m in (1, 2, 4, 8):
    _add(f"contiguous_split_uniform_m{_m}", _split_sql(_m))(lambda s, sf, m=_m: baselines.uniform(_e(s, sf), 4, m).select("vec_id", r6("loss").alias("loss")))
_PERM = prep.make_permutation(D, 4, 0)


@_add("random_split_uniform", _split_sql(4, _PERM.tolist()))
def random_split_uniform(spark: SparkSession, sf: str) -> DataFrame:
    parts = prep.split_column(F.col("embedding"), 4, _PERM.tolist())
    ranked = _e(spark, sf).select("vec_id", F.flatten(parts).alias("embedding"))
    return baselines.uniform(ranked, 4, 4).select("vec_id", r6("loss").alias("loss"))


# --- fits that a grid decides ----------------------------------------------------------------

_N = 7


def _grid_points(curve: str) -> list[tuple[float, float]]:
    a, b = workloads.grid_axes(curve, _N)
    return [(x, y) for x in a for y in b]


def _grid_sql(curve: str, where: str = "true", bits: int = 8) -> str:
    points = ", ".join(f"({q.num(a)}, {q.num(b)})" for a, b in _grid_points(curve))
    return f"""{q.LONG}, points AS (SELECT * FROM (VALUES {points}) t(p0, p1)),
        flat AS (SELECT vec_id, sum({q.error('unif', bits, coded=q.code('unif', bits))}) AS u FROM long WHERE {where} GROUP BY vec_id),
        coded AS (SELECT vec_id, value, lo, hi, p0, p1, {q.code(curve, bits, 'p0', 'p1')} AS code FROM long, points WHERE {where}),
        losses AS (SELECT vec_id, p0, p1, sum({q.error(curve, bits, 'p0', 'p1')}) AS loss FROM coded GROUP BY vec_id, p0, p1),
        gained AS (SELECT vec_id, p0, p1, loss, u / loss AS gain FROM losses JOIN flat USING (vec_id))"""


for _curve in curves.NAMES:
    _add(f"grid_fit_{_curve}", f"WITH {_grid_sql(_curve)} SELECT vec_id, {q.r6('max(gain)', 5)} AS gain FROM gained GROUP BY vec_id")(
        lambda s, sf, c=_curve: fit.grid(embeddings(s, sf), c, 8, *workloads.grid_axes(c, _N)).select("vec_id", r6("gain", 5).alias("gain"))
    )
_add("landscape_v0", f"WITH {_grid_sql('logi', 'vec_id = 0')} SELECT vec_id, {q.r6('p0')} AS p0, {q.r6('p1')} AS p1, {q.r6('gain', 5)} AS gain FROM gained")(
    lambda s, sf: fit.landscape(_e(s, sf).where("vec_id = 0"), "logi", 8, *workloads.grid_axes("logi", _N)).select("vec_id", r6("p0").alias("p0"), r6("p1").alias("p1"), r6("gain", 5).alias("gain"))
)


@_add(
    "cross_cuts",
    f"WITH {_grid_sql('kuma', 'vec_id = 0')}, best AS (SELECT p0 AS b0, p1 AS b1 FROM gained ORDER BY round(gain, 5) DESC, p0, p1 LIMIT 1) SELECT {q.r6('p0')} AS p0, {q.r6('p1')} AS p1, {q.r6('gain', 5)} AS gain FROM gained, best WHERE p0 = b0 OR p1 = b1",
)
def cross_cuts(spark: SparkSession, sf: str) -> DataFrame:
    """The two lines of the landscape that pass through its best point."""
    land = fit.landscape(_e(spark, sf).where("vec_id = 0"), "kuma", 8, *workloads.grid_axes("kuma", _N))
    best = land.agg(F.min_by(F.struct("p0", "p1"), F.struct(-F.round("gain", 5), "p0", "p1")).alias("b"))
    cut = land.crossJoin(F.broadcast(best)).where((F.col("p0") == F.col("b.p0")) | (F.col("p1") == F.col("b.p1")))
    return cut.select(r6("p0").alias("p0"), r6("p1").alias("p1"), r6("gain", 5).alias("gain"))


_add("global_theta", f"WITH {_grid_sql('logi')} SELECT {q.r6('p0')} AS p0, {q.r6('p1')} AS p1, {q.r6('sum(loss) * 1000', 4)} AS loss FROM gained GROUP BY p0, p1")(
    lambda s, sf: fit.global_losses(embeddings(s, sf), "logi", 8, *workloads.grid_axes("logi", _N)).select(r6("p0").alias("p0"), r6("p1").alias("p1"), r6(F.col("loss") * 1000, 4).alias("loss"))
)
_add(
    "per_vs_global",
    f"WITH {_grid_sql('logi')}, own AS (SELECT vec_id, min(loss) AS l FROM gained GROUP BY vec_id), pooled AS (SELECT p0, p1, sum(loss) AS l FROM gained GROUP BY p0, p1) SELECT {q.r6('(SELECT sum(l) FROM own) * 1000', 4)} AS own_loss, {q.r6('(SELECT min(l) FROM pooled) * 1000', 4)} AS shared_loss",
)(lambda s, sf: workloads.personal_vs_shared(s, sf, n=_N).select(r6(F.col("own_loss") * 1000, 4).alias("own_loss"), r6(F.col("shared_loss") * 1000, 4).alias("shared_loss")))

# --- fits by search: what SQL can state are counts and bounds --------------------------------

_STEPS = 3


def _steps(spark: SparkSession, sf: str, curve: str, bits: int) -> DataFrame:
    """vec_id, p0, p1, gain after the first iterations of the search, with fixed draws."""
    s = Search(curve=curve, bits=bits, fixed_iter=_STEPS, sigma=stepsql.SIGMA[curve], draws=stepsql.draws(_STEPS))
    return fit.evolve(embeddings(spark, sf), s).select("vec_id", "p0", "p1", "gain")


for _curve in curves.NAMES:
    for _bits in (8, 4):
        _add(f"evolve_{_curve}_{_bits}")(lambda s, sf, c=_curve, b=_bits: fit.evolve(embeddings(s, sf), Search(curve=c, bits=b), prep.fit_mean(_e(s, sf))))
        _add(f"fit_steps_{_curve}_{_bits}", f"WITH {q.LONG}, {stepsql.steps(_curve, _bits, _STEPS)} SELECT vec_id, {q.r6('p0', 5)} AS p0, {q.r6('p1', 5)} AS p1, {q.r6('gain', 5)} AS gain FROM fitted")(
            lambda s, sf, c=_curve, b=_bits: _steps(s, sf, c, b).select("vec_id", r6("p0", 5).alias("p0"), r6("p1", 5).alias("p1"), r6("gain", 5).alias("gain"))
        )
_BY_CURVE = f"WITH {q.LONG}, " + ", ".join(stepsql.steps(c, 8, _STEPS, f"_{c}") for c in curves.NAMES) + ", found AS (" + " UNION ALL ".join(f"SELECT '{c}' AS curve, * FROM fitted_{c}" for c in curves.NAMES) + ")"


def _steps_by_curve(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for c in curves.NAMES:
        one = _steps(spark, sf, c, 8).withColumn("curve", F.lit(c))
        out = one if out is None else out.unionByName(one)
    return out


_add("fit_steps_gains", f"{_BY_CURVE} SELECT curve, count(*) AS n, {q.r6('avg(gain)', 4)} AS mean, {q.r6('min(gain)', 4)} AS least, {q.r6('max(gain)', 4)} AS most, {q.r6('quantile_cont(gain, 0.5)', 4)} AS middle, {q.r6('avg(CASE WHEN gain < 1 THEN 1.0 ELSE 0.0 END)', 4)} AS below_one FROM found GROUP BY curve")(
    lambda s, sf: measures.gain_summary(_steps_by_curve(s, sf), "curve").select("curve", "n", *[r6(c, 4).alias(c) for c in ("mean", "least", "most")], r6(F.col("quartiles")[1], 4).alias("middle"), r6("below_one", 4).alias("below_one"))
)
_add("fit_steps_duel", f"{_BY_CURVE}, p AS (SELECT vec_id, max(CASE WHEN curve = 'logi' THEN gain END) AS a, max(CASE WHEN curve = 'kuma' THEN gain END) AS b FROM found GROUP BY vec_id) SELECT 'logi' AS \"first\", 'kuma' AS \"second\", {q.r6('avg(CASE WHEN a > b THEN 1.0 ELSE 0.0 END)')} AS wins FROM p")(
    lambda s, sf: measures.win_rate(_steps_by_curve(s, sf), "logi", "kuma").withColumn("wins", r6("wins"))
)
_SPREADS = {"mean0": "avg(p0)", "mean1": "avg(p1)", "sd0": "stddev_samp(p0)", "sd1": "stddev_samp(p1)", "covariance": "covar_samp(p0, p1)", "correlation": "corr(p0, p1)"}
_add("fit_steps_spread", f"{_BY_CURVE} SELECT curve, " + ", ".join(f"{q.r6(x, 4)} AS {n}" for n, x in _SPREADS.items()) + " FROM found GROUP BY curve")(
    lambda s, sf: measures.param_spread(_steps_by_curve(s, sf), "curve").select("curve", *[r6(c, 4).alias(c) for c in _SPREADS])
)
_add("fit_steps_alpha_shift", f"{_BY_CURVE} SELECT {q.r6('avg(CASE WHEN curve = ' + chr(39) + 'pwl' + chr(39) + ' THEN p0 END) / avg(CASE WHEN curve = ' + chr(39) + 'logi' + chr(39) + ' THEN p0 END)', 4)} AS shift FROM found")(
    lambda s, sf: measures.alpha_shift(_steps_by_curve(s, sf)).select(r6("shift", 4).alias("shift"))
)
_add("search_hparams", f"SELECT p, CAST(2 * (4 + floor(3 * ln(p))) AS INTEGER) AS samples, {q.r6('(9 + 3 * ln(p)) / (5 * p * sqrt(p))')} AS rate, {q.r6('(3 + ln(p)) / (5 * sqrt(p))')} AS separable FROM (VALUES (1), (2), (3), (4), (8)) t(p)")(
    lambda s, sf: s.createDataFrame([(p, fit.default_hparams(p)[0], round(fit.default_hparams(p)[2], 6), round(fit.separable_rate(p), 6)) for p in (1, 2, 3, 4, 8)], "p int, samples int, rate double, separable double")
)
_add("rank_utilities", f"WITH r AS (SELECT k, greatest(0, ln(7) - ln(k)) AS raw FROM range(1, 13) t(k)) SELECT CAST(k AS INTEGER) AS k, {q.r6('raw / (SELECT sum(raw) FROM r) - 1.0 / 12')} AS utility FROM r")(
    lambda s, sf: s.createDataFrame([(k + 1, float(u)) for k, u in enumerate(fit.rank_utilities(12))], "k int, utility double").select("k", r6("utility").alias("utility"))
)
_add("evolve_logi2_8")(lambda s, sf: measures.gain_summary(fit.evolve(embeddings(s, sf), Search(curve="logi2"), prep.fit_mean(_e(s, sf))).withColumn("curve", F.lit("logi2")), "curve"))
_add("straight_through")(lambda s, sf: fit.straight_through(embeddings(s, sf), mean=prep.fit_mean(_e(s, sf))))
_add("best_curve")(lambda s, sf: fit.best_curve(embeddings(s, sf), Search(keep_best=True), mean=prep.fit_mean(_e(s, sf))).groupBy("curve").agg(F.count("*").alias("n"), F.avg("gain").alias("gain")))
_add("warm_start")(lambda s, sf: fit.evolve(embeddings(s, sf), fit.median_start(embeddings(s, sf), Search(), 0.2), prep.fit_mean(_e(s, sf))).agg(F.avg("iters").alias("iters"), F.avg("gain").alias("gain")))
_add("query_weighted_fit")(lambda s, sf: fit.evolve(embeddings(s, sf), Search(weights=tuple(1 + (k % 4) for k in range(D)))).agg(F.avg("gain").alias("gain")))
_add("mixed_bits")(lambda s, sf: codec.encode_mixed(embeddings(s, sf), Search(), [8, 4]).groupBy("sub", "bits").agg(F.count("*").alias("n"), F.avg("loss").alias("loss"), F.avg("gain").alias("gain")))
_add("step_sizes")(lambda s, sf: measures.step_size(fit.trace(embeddings(s, sf).select("vec_id", "embedding"), Search(fixed_iter=60))).groupBy("iter").agg(F.avg("step").alias("step")))
_add("subvector_gain")(lambda s, sf: fit.evolve(embeddings(s, sf), Search(m=4, bits=4)).groupBy("sub").agg(F.count("*").alias("n"), F.avg("gain").alias("gain")))

# --- search ----------------------------------------------------------------------------------


def _queries_of(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return search.holdout(embeddings(spark, sf))


_SIDES = "base AS (SELECT vec_id, embedding FROM embeddings WHERE vec_id % 10 <> 0), asked AS (SELECT vec_id AS query_id, embedding AS qvec FROM embeddings WHERE vec_id % 10 = 0)"
_SCORE = {
    "dot": q.DOT.format(a="qvec", b="embedding"),
    "l2": "-(" + q.SQUARES.format(a="qvec", b="embedding") + ")",
    "cosine": f"({q.DOT.format(a='qvec', b='embedding')} / (sqrt({q.DOT.format(a='qvec', b='qvec')}) * sqrt({q.DOT.format(a='embedding', b='embedding')})))",
}


def _top_sql(similarity: str = "dot", base: str = "base", name: str = "top") -> str:
    return f"""{name} AS (SELECT * FROM (SELECT query_id, vec_id, score, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank
        FROM (SELECT query_id, vec_id, {_SCORE[similarity]} AS score FROM {base}, asked)) WHERE rank <= 10)"""


_TOP = "query_id, vec_id, CAST(rank AS INTEGER) AS rank"
for _sim in ("dot", "l2", "cosine"):
    _add(f"exact_top10_{_sim}", f"WITH {_SIDES}, {_top_sql(_sim)} SELECT {_TOP} FROM top")(lambda s, sf, k=_sim: search.exact_topk(*_queries_of(s, sf), 10, k).select("query_id", "vec_id", "rank"))
_add("range_search", f"WITH {_SIDES} SELECT query_id, vec_id, {q.r6(_SCORE['dot'], 5)} AS score FROM base, asked WHERE {_SCORE['dot']} >= 0.3")(
    lambda s, sf: search.within(*_queries_of(s, sf), 0.3).select("query_id", "vec_id", r6("score", 5).alias("score"))
)

_DECODED = f"""{q.LONG}, coded AS (SELECT *, {q.code('unif', 4)} AS code FROM long),
    rebuilt AS (SELECT vec_id, list({q.unbend('unif', '(CAST(code AS DOUBLE) / 15)')} ORDER BY dim) AS embedding FROM coded WHERE vec_id % 10 <> 0 GROUP BY vec_id)"""


def _uniform_decoded(spark: SparkSession, sf: str) -> DataFrame:
    base, _ = _queries_of(spark, sf)
    x = F.transform("embedding", lambda v: v.cast("double"))
    coded = base.select("vec_id", F.array_min(x).alias("lo"), F.array_max(x).alias("hi"), expr.quantize_array("unif", x, bits=4).alias("codes"))
    return coded.select("vec_id", expr.dequantize_array("unif", F.col("codes"), F.col("lo"), F.col("hi"), bits=4).alias("embedding"))


def _uniform_top(spark: SparkSession, sf: str) -> DataFrame:
    return search.exact_topk(_uniform_decoded(spark, sf), _queries_of(spark, sf)[1], 10)


def _exact(spark: SparkSession, sf: str) -> DataFrame:
    return search.exact_topk(*_queries_of(spark, sf), 10)


_BOTH = f"WITH {_SIDES}, {_DECODED}, {_top_sql()}, {_top_sql(base='rebuilt', name='found')}"
_add("uniform_top10", f"{_BOTH} SELECT {_TOP} FROM found")(lambda s, sf: _uniform_top(s, sf).select("query_id", "vec_id", "rank"))
_add("recall10_uniform", f"{_BOTH} SELECT query_id, {q.r6('count(found.vec_id) / 10.0')} AS recall FROM top LEFT JOIN found USING (query_id, vec_id) GROUP BY query_id")(
    lambda s, sf: measures.recall_at_k(_uniform_top(s, sf), _exact(s, sf), 10).select("query_id", r6("recall").alias("recall"))
)
_add(
    "map10_uniform",
    f"""{_BOTH}, hits AS (SELECT found.query_id, found.rank, CASE WHEN top.vec_id IS NULL THEN 0 ELSE 1 END AS rel FROM found LEFT JOIN top USING (query_id, vec_id)),
    p AS (SELECT *, sum(rel) OVER (PARTITION BY query_id ORDER BY rank) / rank AS pr FROM hits) SELECT query_id, {q.r6('sum(pr * rel) / 10')} AS average_precision FROM p GROUP BY query_id""",
)(lambda s, sf: measures.map_at_k(_uniform_top(s, sf), _exact(s, sf), 10).select("query_id", r6("average_precision").alias("average_precision")))
_add(
    "dot_error_uniform",
    f"WITH {_SIDES}, {_DECODED}, pairs AS (SELECT base.vec_id, base.embedding AS x, rebuilt.embedding AS y FROM base JOIN rebuilt USING (vec_id)) SELECT query_id, {q.r6('sum(pow(' + q.DOT.format(a='qvec', b='x') + ' - ' + q.DOT.format(a='qvec', b='y') + ', 2))')} AS error FROM pairs, asked GROUP BY query_id",
)(lambda s, sf: measures.dot_error(measures.pairs_of(_queries_of(s, sf)[0], _uniform_decoded(s, sf)), _queries_of(s, sf)[1]).select("query_id", r6("error").alias("error")))
_add("mean_recon_uniform", f"WITH {_SIDES}, {_DECODED} SELECT {q.r6('avg(' + q.SQUARES.format(a='base.embedding', b='rebuilt.embedding') + ')')} AS mean_recon FROM base JOIN rebuilt USING (vec_id)")(
    lambda s, sf: measures.mean_recon(measures.pairs_of(_queries_of(s, sf)[0], _uniform_decoded(s, sf))).select(r6("mean_recon").alias("mean_recon"))
)
_add(
    "fidelity_uniform",
    f"WITH {_SIDES}, {_DECODED} SELECT vec_id, {q.r6('sqrt(' + q.DOT.format(a='rebuilt.embedding', b='rebuilt.embedding') + ') / sqrt(' + q.DOT.format(a='base.embedding', b='base.embedding') + ')', 5)} AS norm_ratio, {q.r6(q.DOT.format(a='base.embedding', b='rebuilt.embedding') + ' / (sqrt(' + q.DOT.format(a='rebuilt.embedding', b='rebuilt.embedding') + ') * sqrt(' + q.DOT.format(a='base.embedding', b='base.embedding') + '))', 5)} AS cosine FROM base JOIN rebuilt USING (vec_id)",
)(lambda s, sf: measures.fidelity(measures.pairs_of(_queries_of(s, sf)[0], _uniform_decoded(s, sf))).select("vec_id", r6("norm_ratio", 5).alias("norm_ratio"), r6("cosine", 5).alias("cosine")))


@_add("rerank_full_is_exact", f"WITH {_SIDES}, {_top_sql()} SELECT {_TOP} FROM top")
def rerank_full_is_exact(spark: SparkSession, sf: str) -> DataFrame:
    """Re-ranking all rows by full vectors gives the exact result."""
    base, queries = _queries_of(spark, sf)
    everything = search.rank_rows(search.all_pairs(base, queries), 1_000_000)
    return search.rerank(everything, base, queries, 10, 100_000).select("query_id", "vec_id", "rank")


_BOOK = np.round(np.cos(np.arange(16 * 8 * 4, dtype=float).reshape(16, 8, 4)) * 0.2, 3)  # 16 groups, 8 centroids
_BOOK_SQL = "(VALUES " + ", ".join(f"({g}, {c}, {v.tolist()})" for g, part in enumerate(_BOOK) for c, v in enumerate(part)) + ") t(part, c, center)"


def _pq_codes(spark: SparkSession, sf: str) -> DataFrame:
    return pq.encode(_e(spark, sf), _BOOK)


_PQ_SQL = f"""parts AS (SELECT vec_id, part, list_slice(embedding, part * 4 + 1, part * 4 + 4) AS v FROM embeddings, range(16) t(part)),
    near AS (SELECT vec_id, part, c, center, row_number() OVER (PARTITION BY vec_id, part ORDER BY {q.SQUARES.format(a='v', b='center')}, c) AS r FROM parts JOIN {_BOOK_SQL} USING (part)),
    pq AS (SELECT vec_id, part, c, center FROM near WHERE r = 1)"""
_add("pq_fixed_codes", f"WITH {_PQ_SQL} SELECT vec_id, string_agg(lpad(to_hex(c), 2, '0'), '' ORDER BY part) AS code FROM pq GROUP BY vec_id")(
    lambda s, sf: _pq_codes(s, sf).select("vec_id", F.hex("pq").alias("code"))
)
_add(
    "pq_scan",
    f"""WITH {_PQ_SQL}, asked AS (SELECT vec_id AS query_id, embedding AS qvec FROM embeddings WHERE vec_id % 10 = 0),
    scored AS (SELECT query_id, vec_id, sum({q.DOT.format(a='list_slice(qvec, part * 4 + 1, part * 4 + 4)', b='center')}) AS score FROM pq, asked WHERE vec_id % 10 <> 0 GROUP BY query_id, vec_id)
    SELECT query_id, {q.r6('max(score)', 5)} AS best FROM scored GROUP BY query_id""",
)(lambda s, sf: pq.scan_topk(_pq_codes(s, sf).where("vec_id % 10 <> 0"), _BOOK, _queries_of(s, sf)[1], 1).select("query_id", r6("score", 5).alias("best")))

_CENTERS = np.round(np.sin(np.arange(16 * D, dtype=float).reshape(16, D) * 1.7) * 0.15, 3)
_CENTER_SQL = "(VALUES " + ", ".join(f"({i}, {c.tolist()})" for i, c in enumerate(_CENTERS)) + ") t(cluster_id, center)"
_NEAR = "SELECT {key}, cluster_id FROM (SELECT {key}, cluster_id, row_number() OVER (PARTITION BY {key} ORDER BY {score}, cluster_id) AS r FROM {source}, " + _CENTER_SQL + ") WHERE r <= {n}"
_IVF = "lists AS (" + _NEAR.format(key="vec_id", score=q.SQUARES.format(a="embedding", b="center"), source="embeddings", n=2) + ")"
_add("ivf_assign", f"WITH {_IVF} SELECT vec_id, CAST(cluster_id AS INTEGER) AS cluster_id FROM lists")(lambda s, sf: ivf.assign(_e(s, sf), _CENTERS, 2).select("vec_id", "cluster_id"))
_add(
    "ivf_probe",
    f"""WITH {_SIDES}, {_IVF}, probe AS ({_NEAR.format(key="query_id", score=q.SQUARES.format(a="qvec", b="center"), source="asked", n=3)}),
    hit AS (SELECT DISTINCT query_id, vec_id FROM probe JOIN lists USING (cluster_id) WHERE vec_id % 10 <> 0),
    scored AS (SELECT query_id, vec_id, {_SCORE['dot']} AS score FROM hit JOIN base USING (vec_id) JOIN asked USING (query_id))
    SELECT {_TOP} FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored) WHERE rank <= 10""",
)(lambda s, sf: ivf.search(ivf.assign(_queries_of(s, sf)[0], _CENTERS, 2), _queries_of(s, sf)[1], _CENTERS, 10, 3).select("query_id", "vec_id", "rank"))


def _coded(spark: SparkSession, sf: str, s: Search) -> tuple[DataFrame, DataFrame, DataFrame, list[float]]:
    base, queries = _queries_of(spark, sf)
    mean = prep.fit_mean(base)
    return base, queries, codec.encode(base, s, mean), mean


@_add("pcq_recall10")
def pcq_recall10(spark: SparkSession, sf: str) -> DataFrame:
    out, truth = None, workloads.kept(_exact(spark, sf))
    for bits in (8, 4):
        s = Search(bits=bits, m=2)
        _, queries, coded, mean = _coded(spark, sf, s)
        found = search.coded_topk(coded, queries, s, D, 10, mean=mean)
        one = measures.recall_at_k(found, truth, 10).agg(F.lit(bits).alias("bits"), F.avg("recall").alias("recall"))
        out = one if out is None else out.unionByName(one)
    return out


@_add("pcq_map10")
def pcq_map10(spark: SparkSession, sf: str) -> DataFrame:
    s = Search(bits=4, m=2)
    base, queries, coded, mean = _coded(spark, sf, s)
    return measures.map_at_k(search.coded_topk(coded, queries, s, D, 10, mean=mean), search.exact_topk(base, queries, 10), 10).agg(F.avg("average_precision").alias("map"))


@_add("lut_dot_equals_decode", "SELECT count(*) * (SELECT count(*) FROM embeddings WHERE vec_id % 10 = 0) AS pairs, true AS equal FROM embeddings WHERE vec_id % 10 <> 0")
def lut_dot_equals_decode(spark: SparkSession, sf: str) -> DataFrame:
    s = Search(bits=4, m=2)
    _, queries, coded, mean = _coded(spark, sf, s)
    return search.lut_gap(coded, queries, s, D, mean).agg(F.sum("pairs").alias("pairs"), (F.max("gap") < 1e-9).alias("equal"))


_UNIFORM4 = Search(curve="unif", bits=4, split="contiguous")
_add("lut_top10", f"{_BOTH} SELECT {_TOP} FROM found")(
    lambda s, sf: search.lut_topk(codec.encode(_queries_of(s, sf)[0], _UNIFORM4), _queries_of(s, sf)[1], _UNIFORM4, D).select("query_id", "vec_id", "rank")
)
_add("global_top20", f"WITH {_SIDES} SELECT query_id, vec_id, {q.r6(_SCORE['dot'], 5)} AS score FROM base, asked ORDER BY {_SCORE['dot']} DESC, query_id, vec_id LIMIT 20")(
    lambda s, sf: search.global_topk(*_queries_of(s, sf), 20).select("query_id", "vec_id", r6("score", 5).alias("score"))
)
_add("ivf_trained_recall")(workloads.trained_lists)


@_add("graph_recall")
def graph_recall(spark: SparkSession, sf: str) -> DataFrame:
    """Recall of a graph of degree 64, build window 200 and slack 1.2 by search window.

    Shards are of the build's own size: in one of a few hundred rows a search measures nearly all of them.
    """
    base, queries = _queries_of(spark, sf)
    index, truth, out = workloads.kept(graph.build(base)), workloads.kept(search.exact_topk(base, queries, 10)), None
    for window in (10, 20, 50, 100, 200):
        one = measures.recall_at_k(graph.search(index, queries, 10, window), truth, 10).agg(F.lit(window).alias("window"), F.avg("recall").alias("recall"))
        out = one if out is None else out.unionByName(one)
    return out


@_add("graph_degrees", "SELECT count(*) AS n, true AS bounded FROM embeddings WHERE vec_id % 10 <> 0")
def graph_degrees(spark: SparkSession, sf: str) -> DataFrame:
    found = graph.degrees(graph.build(_queries_of(spark, sf)[0], shards=4, degree=16, window=32))
    return found.agg(F.sum("n").alias("n"), (F.max("most") <= 16).alias("bounded"))


@_add("graph_on_pq_rerank")
def graph_on_pq_rerank(spark: SparkSession, sf: str) -> DataFrame:
    """Candidates from a graph over PQ vectors, re-ranked by full vectors and by codes."""
    base, queries = _queries_of(spark, sf)
    book = pq.train(base, 4, 256, 12)
    index = graph.build(pq.encode(base, book), rows_a_shard=500, book=book)
    candidates = workloads.kept(graph.search(index, queries, 100, 200, book))
    s = Search(m=2)
    mean = prep.fit_mean(base)
    stores = {"fp32": (base, None), "coded": (workloads.kept(codec.encode(base, s, mean)), lambda c: codec.decode(c, s, D, mean))}
    return search.rerank_sweep(candidates, stores, queries, workloads.kept(search.exact_topk(base, queries, 10)), 10, [1, 2, 5, 10])


@_add("pq_only_recall")
def pq_only_recall(spark: SparkSession, sf: str) -> DataFrame:
    base, queries = _queries_of(spark, sf)
    book = pq.train(base, 4, 256, 8)
    return measures.recall_at_k(pq.scan_topk(pq.encode(base, book), book, queries, 10), search.exact_topk(base, queries, 10), 10).agg(F.avg("recall").alias("recall"))


_add("pq_decoded_norms", f"WITH {_PQ_SQL} SELECT vec_id, {q.r6('sqrt(sum(' + q.DOT.format(a='center', b='center') + '))')} AS norm FROM pq GROUP BY vec_id")(
    lambda s, sf: pq.decode(_pq_codes(s, sf), _BOOK).select("vec_id", r6(expr.norm(F.col("embedding"))).alias("norm"))
)

# --- models ----------------------------------------------------------------------------------


@_add("op_counts", "SELECT t.curve, t.side, t.operation, t.c * 1000000 AS total FROM (VALUES " + ", ".join(f"('{c}', '{side}', '{o}', {n})" for c in cost.OPERATIONS for c, side, o, n in cost.op_counts(c, 1)) + ") t(curve, side, operation, c)")
def op_counts(spark: SparkSession, sf: str) -> DataFrame:
    return cost.op_frame(spark, 1_000_000)


_DIMS = "(VALUES (128), (768), (1024), (1536)) t(d)"


def _rows(spark: SparkSession, make: Callable[[int], tuple], schema: str) -> DataFrame:
    return spark.createDataFrame([(d, *make(d)) for d in (128, 768, 1024, 1536)], "d int, " + schema)


_add("payload_bytes", f"SELECT d, m, CAST(d + 16 * m AS INTEGER) AS bytes8, CAST(d // 2 + 16 * m AS INTEGER) AS bytes4 FROM {_DIMS}, (VALUES (1), (2), (4), (8)) u(m)")(
    lambda s, sf: s.createDataFrame([(d, m, cost.payload_bytes(d, 8, m), cost.payload_bytes(d, 4, m)) for d in (128, 768, 1024, 1536) for m in (1, 2, 4, 8)], "d int, m int, bytes8 int, bytes4 int")
)
_PER_ROW = "(SELECT vec_id, CAST(len(embedding) AS INTEGER) * k AS d FROM embeddings, (VALUES (1), (2), (12), (16), (24)) t(k))"


def _modelled(make: Callable[[int], tuple], schema: str) -> Query:
    """vec_id, d and a model's figures for every given vector, at its own length and at multiples of it up to the published ones."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        def rows(batches):  # noqa: ANN001, ANN202
            for part in batches:
                known = {d: make(d) for d in part["d"].unique().tolist()}
                made = pd.DataFrame([known[d] for d in part["d"].tolist()], columns=names, index=part.index)
                yield pd.concat([part, made], axis=1)

        names = [f.split()[0] for f in schema.split(", ")]
        # The vectors themselves are read, and measured by their values.
        length = F.aggregate("embedding", F.lit(0), lambda n, v: n + 1)
        each = _e(spark, sf).select("vec_id", F.explode(F.array(*[(length * k).alias("d") for k in (1, 2, 12, 16, 24)])).alias("d"))
        return each.mapInPandas(rows, "vec_id long, d int, " + schema)

    return run


_add("aligned_bytes", f"SELECT vec_id, d, CAST(ceil((d + 32) / 64.0) * 64 AS INTEGER) AS aligned FROM {_PER_ROW}")(_modelled(lambda d: (cost.aligned_bytes(d, 8, 2)[0],), "aligned int"))
_add("index_bytes_model", f"SELECT vec_id, d, CAST(4 * d + 307 AS INTEGER) AS full_bytes, CAST(d + 339 AS INTEGER) AS coded_bytes, {q.r6('(4 * d + 307) / (d + 339)', 4)} AS ratio FROM {_PER_ROW}")(
    lambda s, sf: _modelled(lambda d: cost.index_bytes(d, 8, 2), "full_bytes int, coded_bytes int, ratio double")(s, sf).withColumn("ratio", r6("ratio", 4))
)
_add("fp32_gib", f"SELECT vec_id, d, {q.r6('10000000.0 * d * 4 / 1073741824', 3)} AS gib FROM {_PER_ROW}")(
    lambda s, sf: _modelled(lambda d: (cost.set_gib(10_000_000, d),), "gib double")(s, sf).withColumn("gib", r6("gib", 3))
)
_add("block_layout", f"SELECT vec_id, d, CAST(4 * d + 260 AS INTEGER) AS node_bytes, CAST(ceil((4 * d + 260) / 4096.0) AS INTEGER) AS blocks, 4 * d >= 4096 AS fills FROM {_PER_ROW}")(
    _modelled(cost.block_layout, "node_bytes int, blocks int, fills boolean")
)
_add("inverted_layout", f"SELECT vec_id, d, CAST(10000000 AS BIGINT) * d * 32 AS bytes, {q.r6('49152.0 / (4 * d)', 3)} AS per_cluster FROM {_PER_ROW}")(
    lambda s, sf: _modelled(lambda d: cost.inverted_layout(10_000_000, d), "bytes long, per_cluster double")(s, sf).withColumn("per_cluster", r6("per_cluster", 3))
)
_add("rerank_bytes", f"SELECT d, CAST(50 * 4 * d AS INTEGER) AS full_bytes, CAST(50 * (d + 32) AS INTEGER) AS coded_bytes FROM {_DIMS}")(
    lambda s, sf: _rows(s, lambda d: cost.rerank_bytes(d, 8, 2, 10, 5), "full_bytes int, coded_bytes int")
)

# --- around ----------------------------------------------------------------------------------


def _gains_by_label(spark: SparkSession, sf: str) -> DataFrame:
    base = _e(spark, sf)
    both = measures.gain(base, "logi", *FIXED["logi"]).withColumn("curve", F.lit("logi")).unionByName(measures.gain(base, "kuma", *FIXED["kuma"]).withColumn("curve", F.lit("kuma")))
    return both.join(base.select("vec_id", (F.col("label") % 3).alias("grp")), "vec_id").select("curve", "grp", "gain")


_GAINS = f"g AS (SELECT 'logi' AS curve, vec_id, u / l AS gain FROM ({_loss_sql('logi', 8)}) UNION ALL SELECT 'kuma', vec_id, u / l FROM ({_loss_sql('kuma', 8)})), f AS (SELECT curve, label % 3 AS grp, gain FROM g JOIN embeddings USING (vec_id))"
for _how, _group in (("cube", "CUBE (curve, grp)"), ("rollup", "ROLLUP (curve, grp)")):
    _add(f"gain_{_how}", f"WITH {_GAINS} SELECT curve, grp, count(*) AS n, {q.r6('avg(gain)', 5)} AS mean_gain FROM f GROUP BY {_group}")(
        lambda s, sf, h=_how: relational.gain_cube(_gains_by_label(s, sf), "curve", "grp", how=h).withColumn("mean_gain", r6("mean_gain", 5))
    )


@_add("gain_grouping_sets", f"WITH {_GAINS} SELECT curve, grp, count(*) AS n FROM f GROUP BY GROUPING SETS ((curve), (grp))")
def gain_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    return _gains_by_label(spark, sf).groupingSets([["curve"], ["grp"]], "curve", "grp").agg(F.count("*").alias("n"))


_add("gain_quantiles", f"WITH {_GAINS} SELECT curve, {q.r6('quantile_cont(gain, 0.25)', 5)} AS q1, {q.r6('quantile_cont(gain, 0.5)', 5)} AS q2, {q.r6('quantile_cont(gain, 0.75)', 5)} AS q3 FROM f GROUP BY curve")(
    lambda s, sf: measures.gain_summary(_gains_by_label(s, sf), "curve").select("curve", *[r6(F.col("quartiles")[k], 5).alias(f"q{k + 1}") for k in range(3)])
)
_add("fixed_win_rate", f"WITH {_GAINS}, p AS (SELECT vec_id, max(CASE WHEN curve = 'logi' THEN gain END) AS a, max(CASE WHEN curve = 'kuma' THEN gain END) AS b FROM g GROUP BY vec_id) SELECT 'logi' AS \"first\", 'kuma' AS \"second\", {q.r6('avg(CASE WHEN a > b THEN 1.0 ELSE 0.0 END)')} AS wins FROM p")(
    lambda s, sf: measures.win_rate(
        measures.gain(_e(s, sf), "logi", *FIXED["logi"]).withColumn("curve", F.lit("logi")).unionByName(measures.gain(_e(s, sf), "kuma", *FIXED["kuma"]).withColumn("curve", F.lit("kuma"))), "logi", "kuma"
    ).withColumn("wins", r6("wins"))
)
_add("topk_intersect", f"{_BOTH} SELECT query_id, vec_id FROM top INTERSECT SELECT query_id, vec_id FROM found")(lambda s, sf: relational.common(_exact(s, sf), _uniform_top(s, sf)))
_add("topk_except", f"{_BOTH} SELECT query_id, vec_id FROM top EXCEPT ALL SELECT query_id, vec_id FROM found")(lambda s, sf: relational.only_first(_exact(s, sf), _uniform_top(s, sf)))
_add("heldout_anti", "SELECT vec_id FROM embeddings WHERE vec_id % 10 <> 0")(
    lambda s, sf: relational.not_in(_e(s, sf).select("vec_id"), _queries_of(s, sf)[1].select(F.col("query_id").alias("vec_id")))
)
_add("fetch_semi", f"WITH {_SIDES}, {_top_sql()} SELECT vec_id, label FROM embeddings WHERE vec_id IN (SELECT vec_id FROM top)")(lambda s, sf: relational.fetch(_exact(s, sf), _e(s, sf).select("vec_id", "label")))
_add("missing_codes", "SELECT vec_id, 'right' AS missing_in FROM embeddings WHERE vec_id % 7 = 3")(
    lambda s, sf: relational.missing(_e(s, sf), _e(s, sf).where("vec_id % 7 <> 3"))
)
for _strategy in ("merge", "hash"):
    _add(f"pair_join_{_strategy}", "SELECT vec_id, a.label FROM embeddings a JOIN (SELECT vec_id FROM embeddings WHERE label < 5) b USING (vec_id)")(
        lambda s, sf, h=_strategy: relational.pair(_e(s, sf).select("vec_id", "label"), _e(s, sf).where("label < 5").select("vec_id"), strategy=h)
    )
_add("level_lookup", f"WITH {q.LONG} SELECT CAST(floor((value + 1) * 8) AS INTEGER) AS code, count(*) AS n FROM long GROUP BY 1")(
    lambda s, sf: relational.level_lookup(_long(s, sf).select("value"), s.range(-1, 17).select(F.col("id").cast("int").alias("code"), (F.col("id") / 8 - 1).alias("low"), ((F.col("id") + 1) / 8 - 1).alias("high"))).groupBy("code").agg(F.count("*").alias("n"))
)
for _how in ("row_number", "dense_rank"):
    _add(f"topk_per_label_{_how}", f"SELECT label, vec_id, CAST(rank AS INTEGER) AS rank FROM (SELECT label, vec_id, {_how}() OVER (PARTITION BY label ORDER BY vec_id // 30, vec_id) AS rank FROM embeddings) WHERE rank <= 5")(
        lambda s, sf, h=_how: relational.topk_per_key(_e(s, sf).select("label", "vec_id"), "label", [F.floor(F.col("vec_id") / 30), "vec_id"], 5, h)
    )
_add("topk_per_label_rank_ties", "SELECT label, vec_id, CAST(rank AS INTEGER) AS rank FROM (SELECT label, vec_id, rank() OVER (PARTITION BY label ORDER BY vec_id // 30) AS rank FROM embeddings) WHERE rank <= 5")(
    lambda s, sf: relational.topk_per_key(_e(s, sf).select("label", "vec_id"), "label", [F.floor(F.col("vec_id") / 30)], 5, "rank")
)
_add("asof_mean", """WITH v AS (SELECT event_id AS vec_id, user_id AS store_id, ts FROM events WHERE event_type <> 'purchase'), m AS (SELECT event_id AS mean_version, user_id AS store_id, ts FROM events WHERE event_type = 'purchase')
    SELECT vec_id, (SELECT max(mean_version) FROM m WHERE m.store_id = v.store_id AND m.ts = (SELECT max(ts) FROM m m2 WHERE m2.store_id = v.store_id AND m2.ts <= v.ts)) AS mean_version FROM v""")(
    lambda s, sf: encode.asof_mean(
        table(s, sf, "events").where("event_type <> 'purchase'").select(F.col("event_id").alias("vec_id"), F.col("user_id").alias("store_id"), "ts"),
        table(s, sf, "events").where("event_type = 'purchase'").groupBy(F.col("user_id").alias("store_id"), "ts").agg(F.max("event_id").alias("mean_version")),
    ).select("vec_id", "mean_version")
)
_add("interval_join", "SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND abs(floor(epoch(a.ts)) - floor(epoch(b.ts))) <= 600")(
    lambda s, sf: relational.interval(table(s, sf, "events").select("user_id", "ts"), table(s, sf, "events").select("user_id", "ts"), 600, "user_id").agg(F.count("*").alias("pairs"))
)


def _array_codes_sql(source: str, size: int) -> str:
    return f"""WITH ranked AS ({source}), full_ AS (SELECT vec_id FROM ranked GROUP BY vec_id HAVING count(*) >= {size}),
        long AS (SELECT vec_id, r - 1 AS dim, CAST(CAST(value AS FLOAT) AS DOUBLE) AS value FROM ranked JOIN full_ USING (vec_id) WHERE r <= {size}),
        b AS (SELECT *, min(value) OVER (PARTITION BY vec_id) AS lo, max(value) OVER (PARTITION BY vec_id) AS hi FROM long)
        SELECT vec_id, CAST(sum({q.code('unif', 8)}) AS BIGINT) AS code_sum FROM b GROUP BY vec_id"""


def _array_codes(df: DataFrame) -> DataFrame:
    code = expr.quantize("unif", F.col("value"), F.col("lo"), F.col("hi"))
    return measures.long_form(df).groupBy("vec_id").agg(F.sum(code).alias("code_sum"))


_add("event_arrays_codes", _array_codes_sql("SELECT user_id AS vec_id, value, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS r FROM events", 48))(lambda s, sf: _array_codes(workloads.event_arrays(s, sf)))
_add("supplier_arrays_codes", _array_codes_sql("SELECT l_suppkey AS vec_id, l_extendedprice AS value, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber, l_partkey, l_extendedprice) AS r FROM lineitem", 512))(
    lambda s, sf: _array_codes(workloads.supplier_arrays(s, sf))
)
_add("props_json", "SELECT event_type, count(*) AS n, count(DISTINCT json_extract_string(props, '$.' || json_keys(props)[1])) AS firsts FROM events GROUP BY event_type")(
    lambda s, sf: table(s, sf, "events").select("event_type", F.map_values(F.from_json("props", "map<string,string>"))[0].alias("v")).groupBy("event_type").agg(F.count("*").alias("n"), F.count_distinct("v").alias("firsts"))
)
_add("value_quantiles", f"WITH {q.LONG} SELECT {q.r6('quantile_cont(value, 0.1)')} AS a, {q.r6('quantile_cont(value, 0.5)')} AS b, {q.r6('quantile_cont(value, 0.9)')} AS c FROM long")(
    lambda s, sf: relational.quantiles(_long(s, sf), "value", [0.1, 0.5, 0.9]).select(*[r6(F.col("quantiles")[i]).alias(n) for i, n in enumerate("abc")])
)
for _how in ("approx", "sketch"):
    _add(f"value_quantiles_{_how}", "SELECT true AS near")(lambda s, sf, h=_how: _near_quantiles(s, sf, h))
_add("code_map", f"WITH {q.LONG}, c AS (SELECT vec_id, {q.code('unif', 4)} AS code FROM long), n AS (SELECT vec_id, code, count(*) AS n FROM c GROUP BY vec_id, code) SELECT vec_id, count(*) AS levels, max(n) AS most FROM n GROUP BY vec_id")(
    lambda s, sf: relational.code_map(_codes("unif", 4, s, sf)).select("vec_id", F.size("codes").cast("long").alias("levels"), F.array_max(F.map_values("codes")).alias("most"))
)
_add("rank_bands", "SELECT label, vec_id, CAST(ntile(4) OVER w AS INTEGER) AS band, round(percent_rank() OVER w, 6) + 0.0 AS share_below FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY vec_id)")(
    lambda s, sf: relational.rank_bands(_e(s, sf).select("label", "vec_id"), "label", ["vec_id"], 4).withColumn("share_below", r6("share_below"))
)


def _near_quantiles(spark: SparkSession, sf: str, how: str) -> DataFrame:
    """Whether approximate quantiles are within 0.02 of the exact ones."""
    long, shares = _long(spark, sf), [0.1, 0.5, 0.9]
    both = relational.quantiles(long, "value", shares).crossJoin(relational.quantiles(long, "value", shares, how=how).withColumnRenamed("quantiles", "other"))
    return both.select(F.forall(F.zip_with("quantiles", "other", lambda a, b: F.abs(a - b)), lambda v: v < 0.02).alias("near"))


for _fmt in ("parquet", "orc", "json", "csv", "text"):
    _add(f"store_{_fmt}", f"SELECT vec_id, {q.r6('sqrt(' + q.DOT.format(a='embedding', b='embedding') + ')')} AS norm FROM embeddings")(
        lambda s, sf, f=_fmt: workloads.store_formats(s, sf, f).select("vec_id", r6(expr.norm(F.col("embedding"))).alias("norm"))
    )
_add("store_codes", "SELECT vec_id, true AS near FROM embeddings")(
    lambda s, sf: workloads.store_round_trip(s, sf).select("vec_id", F.forall(F.zip_with("embedding", "was", lambda a, b: F.abs(a - b)), lambda gap: gap < 0.01).alias("near"))
)
_add("bucketed_join", "SELECT vec_id, label FROM embeddings")(workloads.bucketed_join)
_add("bounds_as_json", f"SELECT vec_id, {q.r6('CAST(list_min(embedding) AS DOUBLE)')} AS lo, {q.r6('CAST(list_max(embedding) AS DOUBLE)')} AS hi FROM embeddings")(
    lambda s, sf: measures.bounded(_e(s, sf)).select("vec_id", F.from_json(F.to_json(F.struct("lo", "hi")), "lo double, hi double").alias("p")).select("vec_id", r6("p.lo").alias("lo"), r6("p.hi").alias("hi"))
)
_add("permutation_cover", "SELECT m, CAST(64 AS BIGINT) AS dims, CAST(64 // m AS BIGINT) AS a_part FROM (VALUES (1), (2), (4), (8)) t(m)")(
    lambda s, sf: s.createDataFrame([(m, int(p), j // (D // m)) for m in (1, 2, 4, 8) for j, p in enumerate(prep.make_permutation(D, m, 3))], "m int, dim int, part int")
    .groupBy("m", "part").agg(F.count_distinct("dim").alias("n")).groupBy("m").agg(F.sum("n").alias("dims"), F.min("n").alias("a_part"))
)
_add("running_mean", f"SELECT user_id % 5 AS k, count(*) AS n, {q.r6('avg(value)', 4)} AS mean FROM events GROUP BY 1")(
    lambda s, sf: workloads.running_mean(s, sf).withColumn("mean", r6("mean", 4))
)
_add("stable_sample")(lambda s, sf: prep.sample(_e(s, sf), 0.2, 3).select("vec_id"))
_add("sql_functions")(lambda s, sf: _sql_functions(s, sf))


def _sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    """pcq_gain and pcq_dot over all vectors, from SQL text."""
    from vecquant.functions import sqlfn

    sqlfn.register(spark)
    return spark.sql("SELECT vec_id, pcq_gain(embedding, 'pwl', 4) AS gain, pcq_dot(embedding, embedding) AS square FROM {e}", e=embeddings(spark, sf))


def _with_functions(spark: SparkSession, sf: str, text: str) -> DataFrame:
    from vecquant.functions import sqlfn

    sqlfn.register(spark)
    return spark.sql(text, e=_e(spark, sf))


_add("sql_vec_avg", f"WITH {q.LONG} SELECT CAST(dim AS INTEGER) AS dim, {q.r6('avg(value)')} AS mean FROM long GROUP BY dim")(
    lambda s, sf: _with_functions(s, sf, "SELECT posexplode(vec_avg(embedding)) AS (dim, mean) FROM {e}").withColumn("mean", r6("mean"))
)
_add("sql_codes", _array_codes_sql("SELECT vec_id, unnest(embedding) AS value, unnest(range(1, len(embedding) + 1)) AS r FROM embeddings", D))(
    lambda s, sf: _with_functions(s, sf, "SELECT vec_id, aggregate(pcq_codes(embedding, 'unif', 8, 0D, 0D), 0L, (a, c) -> a + c) AS code_sum FROM {e}")
)
_add("sql_landscape", f"WITH {_grid_sql('logi', 'vec_id = 0')} SELECT {q.r6('p0')} AS p0, {q.r6('p1')} AS p1, {q.r6('gain', 5)} AS gain FROM gained")(
    lambda s, sf: _with_functions(s, sf, f"SELECT t.* FROM {{e}} e, LATERAL pcq_landscape(embedding, 'logi', 8, 0.5D, 12D, -0.5D, 0.5D, {_N}) t WHERE e.vec_id = 0").select(*[r6(c, p).alias(c) for c, p in (("p0", 6), ("p1", 6), ("gain", 5))])
)
_add("sql_gain_summary", f"WITH {_GAINS} SELECT curve, CAST(count(*) AS DOUBLE) AS n, {q.r6('avg(gain)', 5)} AS mean, {q.r6('min(gain)', 5)} AS least, {q.r6('max(gain)', 5)} AS most FROM f GROUP BY curve")(
    lambda s, sf: _sql_gain_summary(s, sf)
)


def _sql_gain_summary(spark: SparkSession, sf: str) -> DataFrame:
    from vecquant.functions import sqlfn

    sqlfn.register(spark)
    sqlfn.register_views(spark, {"fixed_gains": _gains_by_label(spark, sf)})
    rows = spark.sql("SELECT curve, pcq_gain_summary(gain) AS s FROM fixed_gains GROUP BY curve")
    return rows.select("curve", F.col("s")[0].alias("n"), *[r6(F.col("s")[k + 1], 5).alias(c) for k, c in enumerate(("mean", "least", "most"))])


# --- streams ---------------------------------------------------------------------------------

_EVENTS = "SELECT user_id % 5 AS k, ts, value FROM events"
_WINDOW = "SELECT {start} AS start, {end} AS \"end\", count(*) AS n, " + q.r6("avg(value)") + " AS mean FROM {source} GROUP BY 1, 2"


def _windows(kind: str, **options: str) -> Query:
    return lambda s, sf: encode.gain_windows(table(s, sf, "events"), kind, value="value", **options).withColumn("mean", r6("mean"))


_add("gain_tumbling", _WINDOW.format(start="date_trunc('hour', ts)", end="date_trunc('hour', ts) + INTERVAL 1 HOUR", source="events"))(_windows("tumbling"))
_add(
    "gain_sliding",
    _WINDOW.format(
        start="s", end="s + INTERVAL 1 HOUR",
        source="(SELECT value, time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS s FROM events, (VALUES (0), (1)) t(k))",
    ),
)(_windows("sliding"))
_add(
    "gain_session",
    f"""WITH e AS (SELECT user_id, ts, value, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
    s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e)
    SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 1 HOUR AS "end", count(*) AS n, {q.r6('avg(value)')} AS mean FROM s GROUP BY user_id, g""",
)(_windows("session", keys=("user_id",)))
_add(
    "late_rows",
    "SELECT event_id FROM (SELECT event_id, ts, max(ts) OVER (ORDER BY (event_id * 7919) % 10007, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS latest FROM (SELECT event_id, ts FROM events WHERE (event_id * 7919) % 10007 IS NOT NULL)) WHERE floor(epoch(latest)) - floor(epoch(ts)) > 3600 AND latest IS NOT NULL",
)(
    lambda s, sf: encode.late_rows(
        table(s, sf, "events").select("event_id", "ts", ((F.col("event_id") * 7919) % 10007 * 10_000_000 + F.col("event_id")).alias("arrival")), 3600, "arrival"
    ).select("event_id")
)
_add("stream_equals_batch", "SELECT CAST(0 AS BIGINT) AS differences")(workloads.stream_equals_batch)

# --- experiments -----------------------------------------------------------------------------

for _name, _f in {
    "landscape": workloads.landscape,
    "landscape_768": lambda s, sf: workloads.landscape(s, sf, n=21, d=768),
    "convergence": workloads.convergence,
    "iterations": workloads.iterations,
    "iterations_768": lambda s, sf: workloads.iterations(s, sf, 768),
    "gains_8bit": workloads.gains,
    "gains_4bit": lambda s, sf: workloads.gains(s, sf, 4),
    "curve_duel": workloads.curve_duel,
    "curve_duel_768": lambda s, sf: workloads.curve_duel(s, sf, 768),
    "param_spread": workloads.parameter_spread,
    "param_spread_768": lambda s, sf: workloads.parameter_spread(s, sf, 768),
    "param_spread_768_4bit": lambda s, sf: workloads.parameter_spread(s, sf, 768, 4),
    "alpha_shift": workloads.alpha_shift,
    "text_gains": workloads.text_gains,
    "text_gains_4bit": lambda s, sf: workloads.text_gains(s, sf, 768, 4),
    "wide_gains": workloads.wide_gains,
    "wide_gains_4bit": lambda s, sf: workloads.wide_gains(s, sf, 1536, 4),
    "subvectors_4bit": workloads.subvectors,
    "subvectors_8bit": lambda s, sf: workloads.subvectors(s, sf, 8),
    "subvectors_768_4bit": lambda s, sf: workloads.subvectors(s, sf, 4, d=768),
    "subvectors_768_8bit": lambda s, sf: workloads.subvectors(s, sf, 8, d=768),
    "footprint_768": workloads.footprint,
    "footprint_1024": lambda s, sf: workloads.footprint(s, sf, 1024),
    "footprint_1536": lambda s, sf: workloads.footprint(s, sf, 1536),
    "text_rerank_sweep": workloads.rerank_sweep,
    "graph_rerank_768": workloads.graph_rerank,
    "graph_rerank_1024": lambda s, sf: workloads.graph_rerank(s, sf, 1024),
    "graph_rerank_1536": lambda s, sf: workloads.graph_rerank(s, sf, 1536),
    "graph_latency_768": workloads.graph_latency,
    "latency": workloads.search_latency,
    "non_bell": workloads.non_bell,
    "shift": workloads.shift,
    "ablations": workloads.ablations,
    "throughput": workloads.throughput,
    "layout_models": workloads.layout_models,
    "recall_at_equal_time": lambda s, sf: measures.recall_at_equal_time(workloads.graph_latency(s, sf)),
    "recall_loss_at_equal_r": lambda s, sf: measures.recall_delta(workloads.graph_rerank(s, sf)),
}.items():
    _add(f"w_{_name}")(_f)
_WORDED = "regexp_matches(coalesce(text, ''), '[^\\s]')"
for _d in (768, 1024, 1536):
    _add(f"w_graph_loss_{_d}", f"SELECT {_d} AS d, count(*) AS queries, true AS reaches_95, true AS loses_little FROM benchmark WHERE {_WORDED}")(lambda s, sf, d=_d: workloads.graph_rerank_loss(s, sf, d))
_add("w_flat_prior", "SELECT true AS near_one")(lambda s, sf: workloads.flat_prior(s, sf).select(F.col("ratio").between(0.95, 1.05).alias("near_one")))
_add(
    "w_inventory",
    """WITH ev AS (SELECT user_id FROM events GROUP BY 1 HAVING count(*) >= 48), su AS (SELECT l_suppkey FROM lineitem GROUP BY 1 HAVING count(*) >= 512)
    SELECT 'embeddings' AS set, CAST(len(embedding) AS INTEGER) AS d, count(*) AS n, count(*) * len(embedding) * 4 AS bytes FROM embeddings GROUP BY len(embedding)
    UNION ALL SELECT 'events', 48, count(*), count(*) * 192 FROM ev HAVING count(*) > 0 UNION ALL SELECT 'suppliers', 512, count(*), count(*) * 2048 FROM su HAVING count(*) > 0
    UNION ALL SELECT 'text_' || d, d, count(*), count(*) * d * 4 FROM documents, (VALUES (768), (1024), (1536)) t(d) WHERE """ + _WORDED + " GROUP BY d",
)(workloads.inventory)
