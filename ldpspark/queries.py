"""All queries of the library: name -> (Spark query, DuckDB text or None where SQL cannot say it)."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ldpspark.erm import losses
from ldpspark.erm.crossval import cross_validated
from ldpspark.erm.descent import STREAMED, Model, minibatch, participating, prepared, sgd, sliced, train
from ldpspark.erm.projection import matrix, project
from ldpspark.functions import constants as C
from ldpspark.functions import sqlfuncs
from ldpspark.functions.rng import choice, uniform
from ldpspark.functions.rng import uniform_sql as u
from ldpspark.operators import audit, budget, relops
from ldpspark.operators import categorical as cat
from ldpspark.operators import estimate as est
from ldpspark.operators import measure as mea
from ldpspark.operators import mixed as mix
from ldpspark.operators import numeric as num
from ldpspark.oracle import sql as O
from ldpspark.plans import experiments as ex
from ldpspark.plans.schema import TupleSpec, discretised, features
from ldpspark.plans.views import CAT3, LI18, LI23, LINE_KEY, NET, NUM4, NUM6, WIDE_SQL, users, users_sql, wide
from ldpspark.sources.stored import stored
from ldpspark.sources.tables import TABLES, load
from ldpspark.streaming import stream

Query = Callable[[SparkSession, str], DataFrame]
EPS, BETA, LAM = 1.0, 0.05, 1e-4
NAMES4 = [a.name for a in NUM4.numerics]
SMALL = TupleSpec("small", NUM4.numerics, CAT3.categoricals, LINE_KEY)

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def lit_table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def num4(spark: SparkSession, sf: str) -> DataFrame:
    return users(spark, sf, NUM4)


SRC4, SRC3 = users_sql(NUM4), users_sql(CAT3)
c1 = C.report_scale(EPS)

# --- privacy primitives -------------------------------------------------------------------------

_CASES = [("one_coordinate", 1), ("one_coordinate", 3), ("coin_flip", 1), ("halfspace_repaired", 2), ("halfspace_repaired", 3), ("halfspace_repaired", 4), ("orthogonal", 4), ("orthogonal", 6)]


#: Attributes whose signs make the extreme inputs that occur, in this order.
_SIGNED = ["discount", "tax", "quantity", "price"]


def _inputs_sql(mechanism: str, d: int) -> str:
    """Number of unlike inputs of a mechanism that the users of a table have."""
    return f"(SELECT count(DISTINCT line_no) FROM v WHERE line_no < {d})" if mechanism == "orthogonal" else f"(SELECT count(DISTINCT ({', '.join(f'{x} >= 0' for x in _SIGNED[:d])},)) FROM v)"


@query("audit_exact", f"WITH v AS (SELECT DISTINCT {', '.join(_SIGNED)}, line_no FROM {users_sql(SMALL)} s) " + " UNION ALL ".join(f"SELECT '{m}' AS mechanism, {k}::INT AS d, 1.0::double AS eps, 1.0::double AS effective, {_inputs_sql(m, k)}::INT AS inputs" for m, k in _CASES))
def _(spark, sf):
    sign = [F.when(F.col(x) >= 0, 1).otherwise(-1).alias(x) for x in _SIGNED]
    seen = users(spark, sf, SMALL).select(*sign, "line_no").distinct().collect()
    inputs = [sorted({r["line_no"] for r in seen if r["line_no"] < k} if m == "orthogonal" else {tuple(r[x] for x in _SIGNED[:k]) for r in seen}) for m, k in _CASES]
    counts = lit_table(spark, [(m, k, len(i)) for (m, k), i in zip(_CASES, inputs)], "mechanism string, d int, inputs int")
    found = audit.exact_epsilon(spark, [(m, k, EPS) for m, k in _CASES], inputs)
    return found.withColumn("effective", F.round("effective", 9)).join(F.broadcast(counts), ["mechanism", "d"])


@query("audit_empirical", f"""
WITH k AS (SELECT ukey FROM {SRC4} s),
a AS (SELECT j, sign, count(*) AS a FROM {O.one_coordinate("(SELECT ukey, 1.0::double AS x, 1.0::double AS y FROM k)", ["x", "y"], EPS)} r GROUP BY j, sign),
b AS (SELECT j, sign, count(*) AS b FROM {O.one_coordinate("(SELECT ukey, -1.0::double AS x, -1.0::double AS y FROM k)", ["x", "y"], EPS)} r GROUP BY j, sign)
SELECT j, sign, coalesce(a, 0) AS a, coalesce(b, 0) AS b, round(ln(greatest(a, 1)::double / greatest(b, 1)), 9) AS log_ratio FROM a FULL JOIN b USING (j, sign)""")
def _(spark, sf):
    k = num4(spark, sf).select("ukey")
    ends = [k.select("ukey", F.lit(v).alias("x"), F.lit(v).alias("y")) for v in (1.0, -1.0)]
    out = audit.empirical_epsilon(*[num.one_coordinate_report(e, ["x", "y"], EPS) for e in ends], "j", "sign")
    return out.withColumn("log_ratio", F.round("log_ratio", 9))


_DIMS = range(1, 13)
_BINOM = "(factorial(({n})::INT) / (factorial(({k})::INT) * factorial(({n} - ({k}))::INT)))::double"
_CONST = f"""
SELECT d::INT AS d, cd::BIGINT AS size, round(b, 9) AS scale, round(pp, 9) AS p_printed, round(exp(1) * cd / ((exp(1) - 1) * cd + 2 ** d), 9) AS p_repaired FROM (
  SELECT *, (2 ** d + cd * (exp(1) - 1)) / ({_BINOM.format(n='(d - 1)', k='(case when d % 2 = 1 then (d - 1) // 2 else d // 2 end)')} * (exp(1) - 1)) AS b, exp(1) / (exp(1) + 1) AS pp FROM (
    SELECT range AS d, case when range % 2 = 1 then 2 ** (range - 1) else 2 ** (range - 1) - {_BINOM.format(n='range', k='(range // 2)')} / 2 end AS cd FROM range(1, 13)))"""


def _lengths_sql(most: int) -> str:
    """Customers by their number of orders: a customer of d orders has a record of d numbers."""
    return f"(SELECT d, count(*) AS customers FROM (SELECT count(*) AS d FROM orders GROUP BY o_custkey) WHERE d <= {most} GROUP BY d)"


def by_length(spark: SparkSession, sf: str, constants: DataFrame) -> DataFrame:
    """Adds to the constants of each d how many customers have a record of that length."""
    d = load(spark, sf, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).cast("int").alias("d"))
    return constants.join(d.groupBy("d").agg(F.count(F.lit(1)).alias("customers")), "d", "left").fillna(0, "customers")


@query("halfspace_constants", f"SELECT c.*, coalesce(customers, 0) AS customers FROM ({_CONST}) c LEFT JOIN {_lengths_sql(12)} USING (d)")
def _(spark, sf):
    rows = [(d, C.halfspace_size(d), C.halfspace_scale(d, EPS), C.halfspace_prob(d, EPS, "printed"), C.halfspace_prob(d, EPS)) for d in _DIMS]
    t = lit_table(spark, rows, "d int, size long, scale double, p_printed double, p_repaired double")
    return by_length(spark, sf, t.select("d", "size", *[F.round(x, 9).alias(x) for x in ("scale", "p_printed", "p_repaired")]))


@query("halfspace_violation", f"""
WITH k AS ({_CONST}), v AS (SELECT *, unnest(['printed', 'repaired']) AS variant FROM k WHERE d <= 8),
g AS (SELECT d, sum(case when 2 * a > d then w * (2 * a - d) end) / d AS up, -sum(case when 2 * a <= d then w * (2 * a - d) end) / d AS down
      FROM (SELECT d, a, {_BINOM.format(n='d', k='a')} AS w FROM (SELECT d, unnest(range(0, d + 1)) AS a FROM k WHERE d <= 8)) GROUP BY d)
SELECT d, variant, round(case when variant = 'printed' then 1 + ln((2 ** d - size) / size) else 1.0 end, 6) AS effective,
       round(scale * (p * up / size + (1 - p) * -down / (2 ** d - size)), 6) AS bias, coalesce(customers, 0) AS customers
FROM (SELECT v.*, case when variant = 'printed' then p_printed else p_repaired end AS p FROM v) JOIN g USING (d) LEFT JOIN {_lengths_sql(8)} USING (d)""")
def _(spark, sf):
    rows = [(d, v, C.effective_epsilon(d, EPS, v), C.halfspace_bias(d, EPS, v)) for d in range(1, 9) for v in ("printed", "repaired")]
    t = lit_table(spark, rows, "d int, variant string, effective double, bias double")
    return by_length(spark, sf, t.select("d", "variant", F.round("effective", 6).alias("effective"), F.round("bias", 6).alias("bias")))


@query("budget_ledger", "SELECT user_id, count(*) AS reports, 0.5::double * count(*) AS spent FROM events GROUP BY user_id")
def _(spark, sf):
    return budget.ledger(load(spark, sf, "events").select("user_id", F.lit(0.5).alias("eps")), "user_id")


@query("snapshot_ledger", "SELECT user_id, count(DISTINCT floor(epoch(ts) / 604800)) AS periods, 0.5::double AS eps_per_period, 0.5::double * count(DISTINCT floor(epoch(ts) / 604800)) AS eps_joint FROM events GROUP BY user_id")
def _(spark, sf):
    return budget.snapshot_ledger(stream.timed(load(spark, sf, "events")), "user_id", "ts", "7 days", 0.5)


_OWN_EPS = "case when l_linestatus = 'F' then 0.5 else 2.0 end"
_OWN_VIEW = f"(SELECT {', '.join(a.sql() + ' AS ' + a.name for a in NUM4.numerics)}, concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, cast(round(l_extendedprice * 100) as bigint)) AS ukey, ({_OWN_EPS})::double AS eps FROM lineitem)"
_OWN_TILT = {e: 1 / (2 * C.report_scale(e)) for e in (0.5, 2.0)}


@query("personal_epsilon_mean", f"""
WITH r AS (SELECT j, eps, case when {u('ukey', 'toss')} < {O.pick('j', NAMES4)} * ((exp(eps) - 1) / (2 * (exp(eps) + 1))) + 0.5 then 1 else -1 end AS sign
           FROM (SELECT *, floor({u('ukey', 'attr')} * 4)::INT AS j FROM {_OWN_VIEW} v) w)
SELECT {O.pick('j', [f"'{x}'" for x in NAMES4])} AS attr, round(4 * sum(sign * case when eps = 0.5 then {O.d(C.report_scale(0.5))} else {O.d(C.report_scale(2.0))} end) / (SELECT count(*) FROM r), 9) AS estimate FROM r GROUP BY j""")
def _(spark, sf):
    raw = load(spark, sf, "lineitem")
    keyed = raw.select(F.concat_ws("|", *[F.expr(f"cast({k} as string)") for k in LINE_KEY]).alias("ukey"), *[F.expr(a.sql()).alias(a.name) for a in NUM4.numerics], F.expr(f"cast({_OWN_EPS} as double)").alias("eps"))
    sent = num.one_coordinate_report(keyed, NAMES4, eps_col="eps")
    sums = sent.groupBy("j", "eps").agg(F.sum("sign").alias("total"), F.count(F.lit(1)).alias("reports"))
    scale = F.when(F.col("eps") == 0.5, C.report_scale(0.5)).otherwise(C.report_scale(2.0))
    n = F.sum("reports").over(Window.partitionBy())
    label = F.element_at(F.array(*[F.lit(x) for x in NAMES4]), F.col("j") + 1)
    each = sums.withColumn("n", n).groupBy("j").agg(F.sum(F.col("total") * scale).alias("t"), F.first("n").alias("n"))
    return each.select(label.alias("attr"), F.round(4 * F.col("t") / F.col("n"), 9).alias("estimate"))


@query("extremes", f"""
WITH v AS (SELECT * FROM {SRC4} s)
SELECT attr, round(avg(x), 9) AS identity, round(avg(z), 9) AS noise FROM (""" + " UNION ALL ".join(f"SELECT '{n}' AS attr, {n} AS x, 2 * {u('ukey', f'noise:{n}')} - 1 AS z FROM v" for n in NAMES4) + ") t GROUP BY attr")
def _(spark, sf):
    v = num4(spark, sf)
    a = est.mean_dense(num.identity(v, NAMES4), NAMES4).select("attr", F.round("estimate", 9).alias("identity"))
    return a.join(est.mean_dense(num.pure_noise(v, NAMES4), NAMES4).select("attr", F.round("estimate", 9).alias("noise")), "attr")


# --- numeric means ------------------------------------------------------------------------------

@query("mean_laplace", "WITH v AS (SELECT * FROM " + SRC4 + " s) SELECT attr, round(avg(x), 6) AS estimate FROM (" + " UNION ALL ".join(
    f"SELECT '{n}' AS attr, {n} - 8.0::double * sign({u('ukey', f'lap:{n}')} - 0.5) * ln(greatest(1 - 2 * abs({u('ukey', f'lap:{n}')} - 0.5), 2::double ** -53)) AS x FROM v" for n in NAMES4) + ") t GROUP BY attr")
def _(spark, sf):
    return est.mean_dense(num.laplace_report(num4(spark, sf), NAMES4, EPS), NAMES4).withColumn("estimate", F.round("estimate", 6))


for _variant in ("printed", "repaired"):

    @query(f"mean_halfspace_{_variant}", O.halfspace(SRC4, NAMES4, EPS, _variant))
    def _(spark, sf, variant=_variant):
        return est.mean_halfspace(num.halfspace_report(num4(spark, sf), NAMES4, EPS, variant), NAMES4, EPS)


@query("mean_one_coordinate", O.mean_sparse(O.one_coordinate(SRC4, NAMES4, EPS), NAMES4, EPS))
def _(spark, sf):
    return est.mean_sparse(num.one_coordinate_report(num4(spark, sf), NAMES4, EPS), NAMES4, EPS)


@query("mean_public_hash", O.mean_sparse(O.one_coordinate(SRC4, NAMES4, EPS, public=True), NAMES4, EPS))
def _(spark, sf):
    return est.mean_sparse(num.one_coordinate_report(num4(spark, sf), NAMES4, EPS, attr_choice="public_hash"), NAMES4, EPS)


@query("mean_cohort", O.mean_sparse(O.one_coordinate(SRC4, NAMES4, EPS), NAMES4, EPS, cohort=True))
def _(spark, sf):
    return est.mean_sparse(num.one_coordinate_report(num4(spark, sf), NAMES4, EPS), NAMES4, EPS, "cohort")


@query("single_numeric", f"""
SELECT 'one_coordinate' AS method, estimate FROM ({O.mean_sparse(O.one_coordinate(SRC4, ['quantity'], EPS), ['quantity'], EPS)}) a
UNION ALL SELECT 'half_space', estimate FROM ({O.halfspace(SRC4, ['quantity'], EPS, 'repaired')}) b""")
def _(spark, sf):
    v, one = num4(spark, sf), ["quantity"]
    a = est.mean_sparse(num.one_coordinate_report(v, one, EPS), one, EPS).select(F.lit("one_coordinate").alias("method"), "estimate")
    return a.unionByName(est.mean_halfspace(num.halfspace_report(v, one, EPS), one, EPS).select(F.lit("half_space").alias("method"), "estimate"))


_DS = (1, 6, 23)
_GROUPS = f"(SELECT return_flag, count(*) AS n FROM {SRC3} s GROUP BY return_flag)"


def groups(spark: SparkSession, sf: str) -> list[tuple[int, int]]:
    """(return flag, users): collections of different size."""
    return [(r["return_flag"], r["count"]) for r in users(spark, sf, CAT3).groupBy("return_flag").count().collect()]


_BERN = "round((b * l + sqrt(b * b * l * l + 4 * n * a * l)) / (2 * n), 9) AS radius"


@query("mean_radius", f"""
SELECT return_flag, n, d, {_BERN} FROM (SELECT return_flag, n, d, ln(2 * d / 0.05::double) AS l, 2 * c * c * d AS a, 4::double / 3 * c * d AS b FROM
  {_GROUPS}, (SELECT unnest([1, 6, 23])::INT AS d), (SELECT (exp(1) + 1) / (exp(1) - 1) AS c))""")
def _(spark, sf):
    return lit_table(spark, [(flag, n, d, C.mean_radius(n, d, EPS, BETA)) for flag, n in groups(spark, sf) for d in _DS], "return_flag int, n long, d int, radius double").withColumn("radius", F.round("radius", 9))


@query("frequency_radius", f"""
SELECT return_flag, n, d, k, {_BERN} FROM (SELECT return_flag, n, d, k, ln(2 * k / 0.05::double) AS l, 2 * d * c * c AS a, 2::double / 3 * (d * c + 1) AS b FROM
  {_GROUPS}, (SELECT unnest([1, 6, 23])::INT AS d), (SELECT unnest([2, 25])::INT AS k), (SELECT (exp(1) + 1) / (exp(1) - 1) AS c))""")
def _(spark, sf):
    rows = [(flag, n, d, k, C.frequency_radius(n, d, k, EPS, BETA)) for flag, n in groups(spark, sf) for d in _DS for k in (2, 25)]
    return lit_table(spark, rows, "return_flag int, n long, d int, k int, radius double").withColumn("radius", F.round("radius", 9))


@query("variance_grid", f"""
WITH g AS (SELECT d, cd, e FROM (SELECT d, size AS cd FROM ({_CONST}) WHERE d IN (1, 2, 6, 12)), (SELECT unnest([0.5, 1.0, 2.0])::double AS e)),
h AS (SELECT *, (2 ** d + cd * (exp(e) - 1)) / ({_BINOM.format(n='(d - 1)', k='(case when d % 2 = 1 then (d - 1) // 2 else d // 2 end)')} * (exp(e) - 1)) AS b FROM g)
SELECT d, e AS eps, round(8 * d * d / (e * e), 6) AS laplace, round(b * b - square, 6) AS half_space, round(((exp(e) + 1) / (exp(e) - 1)) ** 2 * d - square, 6) AS one_coordinate FROM h, (SELECT avg(price * price) AS square FROM {SRC4} s)""")
def _(spark, sf):
    square = num4(spark, sf).agg(F.avg(F.col("price") * F.col("price"))).first()[0]
    rows = [(d, e, *C.variances(d, e, square).values()) for d in (1, 2, 6, 12) for e in (0.5, 1.0, 2.0)]
    t = lit_table(spark, rows, "d int, eps double, laplace double, half_space double, one_coordinate double")
    return t.select("d", "eps", *[F.round(x, 6).alias(x) for x in ("laplace", "half_space", "one_coordinate")])


@query("central_contrast", "WITH v AS (SELECT * FROM " + SRC4 + " s), e AS (" + " UNION ALL ".join(f"SELECT '{n}' AS attr, avg({n}) AS x, count(*) AS n FROM v" for n in NAMES4) + f""")
SELECT attr, round(x - 8.0::double / n * sign({u('attr', 'central')} - 0.5) * ln(greatest(1 - 2 * abs({u('attr', 'central')} - 0.5), 2::double ** -53)), 9) AS estimate FROM e""")
def _(spark, sf):
    return est.central_laplace(num4(spark, sf), NAMES4, EPS).withColumn("estimate", F.round("estimate", 9))


# --- frequencies --------------------------------------------------------------------------------

_SURVEY = "(SELECT l.doc_id::varchar AS ukey, case when toxic = 1 then 1 else -1 end AS answer FROM labels l JOIN documents d USING (doc_id))"


def survey(spark: SparkSession, sf: str) -> DataFrame:
    docs = load(spark, sf, "documents").select("doc_id")
    return load(spark, sf, "labels").join(docs, "doc_id").select(F.col("doc_id").cast("string").alias("ukey"), F.when(F.col("toxic") == 1, 1).otherwise(-1).alias("answer"))


@query("survey_fair_coin", f"""
SELECT count(*) AS n, (1 + 2.0::double * sum(case when {u('ukey', 'survey:h')} < 0.5 then answer when {u('ukey', 'survey:r')} < 0.5 then 1 else -1 end) / count(*)) / 2 AS positive, {O.d(C.fair_coin_epsilon(0.5))} AS eps FROM {_SURVEY} s""")
def _(spark, sf):
    return est.proportion(cat.survey_report(survey(spark, sf), "answer"), 2.0).withColumn("eps", F.lit(C.fair_coin_epsilon(0.5)))


@query("survey_binary", f"SELECT count(*) AS n, (1 + {O.d(c1)} * sum(case when {u('ukey', 'toss')} < {O.d(C.keep_probability(EPS))} then answer else -answer end) / count(*)) / 2 AS positive FROM {_SURVEY} s")
def _(spark, sf):
    return est.proportion(cat.coin_flip_report(survey(spark, sf), "answer", EPS), c1)


_PHI = lambda s, v, label: f"(case when {u(f'({s}::varchar || chr(124) || {v}::varchar)', f'phi:{label}')} < 0.5 then 1 else -1 end)"


@query("freq_random_projection", f"""
WITH v AS (SELECT * FROM {SRC3} s0), m AS (SELECT greatest(1, ceil(ln(4::double) * ln(2 / 0.05::double) / (ln(6 / 0.05::double) / count(*))))::BIGINT AS m FROM v),
r AS (SELECT s, {_PHI('s', 'return_flag', 'flag')} * (case when {u('ukey', 'flipflag')} < {O.d(C.keep_probability(EPS))} then 1 else -1 end) AS sign FROM (SELECT *, floor({u('ukey', 'rowflag')} * m)::INT AS s FROM v, m) z),
t AS (SELECT s, sum(sign)::BIGINT AS total, count(*) AS n FROM r GROUP BY s)
SELECT code, {O.d(c1)} * sum(total * {_PHI('s', 'code', 'flag')}) / sum(n) AS estimate FROM t, (SELECT range::INT AS code FROM range(3)) GROUP BY code""")
def _(spark, sf):
    v = users(spark, sf, CAT3)
    m = C.projection_rows(3, v.count(), EPS, BETA)
    return est.decode_projection(cat.random_projection_report(v, "return_flag", m, EPS, label="flag"), 3, EPS, "flag")


@query("projection_distortion", f"""
WITH v AS (SELECT DISTINCT floor({u('ukey', 'rowdemo')} * 64)::INT AS s, line_no FROM {SRC3} s0),
p AS (SELECT s, code, {_PHI('s', 'code', 'demo')} AS sign FROM (SELECT DISTINCT s FROM v), (SELECT DISTINCT line_no AS code FROM v)),
i AS (SELECT a.code AS l, b.code AS r, sum(a.sign * b.sign) / 64::double AS inner_product FROM p a JOIN p b USING (s) WHERE a.code < b.code GROUP BY 1, 2)
SELECT count(*) AS pairs, max(abs(inner_product)) AS max_inner, round(sqrt(avg(inner_product * inner_product)), 9) AS rms_inner FROM i""")
def _(spark, sf):
    # the rows that users draw and the values that they have
    v = users(spark, sf, CAT3).select(choice("ukey", "rowdemo", 64).alias("s"), F.col("line_no").alias("code")).distinct()
    grid = v.select("s").distinct().crossJoin(v.select("code").distinct())
    return mea.projection_distortion(grid.withColumn("sign", cat.random_sign(F.col("s"), F.col("code"), "demo", 42)), 64).withColumn("rms_inner", F.round("rms_inner", 9))


_LINE7 = O.orthogonal(SRC3, "line_no", 7, EPS)


@query("freq_orthogonal", _LINE7)
def _(spark, sf):
    return est.decode_orthogonal(cat.orthogonal_report(users(spark, sf, CAT3), "line_no", 7, EPS), 7, EPS)


@query("freq_orthogonal_fast", _LINE7)
def _(spark, sf):
    return est.decode_fast(cat.orthogonal_report(users(spark, sf, CAT3), "line_no", 7, EPS), 7, EPS)


_QTY = "concat_ws('|', " + ", ".join(f"cast({k} as varchar)" for k in LINE_KEY) + ")"


@query("histogram_numeric", O.orthogonal(f"(SELECT {_QTY} AS ukey, l_quantity::INT - 1 AS q FROM lineitem)", "q", 50, EPS, "q"))
def _(spark, sf):
    v = load(spark, sf, "lineitem").select(F.concat_ws("|", *[F.expr(f"cast({k} as string)") for k in LINE_KEY]).alias("ukey"), discretised("l_quantity", [float(x) for x in range(2, 51)]).alias("q"))
    return est.decode_orthogonal(cat.orthogonal_report(v, "q", 50, EPS, label="q"), 50, EPS)


@query("exact_means", "WITH v AS (SELECT * FROM " + SRC4 + " s) " + " UNION ALL ".join(f"SELECT '{n}' AS attr, round(avg({n}), 9) AS exact FROM v" for n in NAMES4))
def _(spark, sf):
    return est.exact_mean(num4(spark, sf), NAMES4).withColumn("exact", F.round("exact", 9))


_COLS3 = [(x.name, x.k) for x in CAT3.categoricals]


@query("exact_histogram", O.histogram(SRC3, _COLS3))
def _(spark, sf):
    return est.exact_histogram(users(spark, sf, CAT3), _COLS3)


# --- many attributes ----------------------------------------------------------------------------

for _name, _oracle in (("multi_split", "projection"), ("multi_split_orthogonal", "orthogonal")):

    @query(_name, O.split_frequencies(CAT3, EPS, _oracle, BETA))
    def _(spark, sf, oracle=_oracle):
        v = users(spark, sf, CAT3)
        sent = mix.split_report(v, CAT3, EPS, oracle=oracle, n=v.count(), beta=BETA)
        return mix.mixed_frequencies(mix.split_sums(sent), CAT3, EPS / CAT3.d, oracle=oracle, factor=1.0)


@query("multi_composite", f"""
WITH cell AS ({O.orthogonal(f"(SELECT ukey, (return_flag * 2 + line_status) * 7 + line_no AS cell FROM {SRC3} b)", "cell", 42, EPS, "cell")})
SELECT attr, code, round(sum(estimate), 9) AS estimate FROM (
  SELECT 'return_flag' AS attr, code // 14 AS code, estimate FROM cell UNION ALL SELECT 'line_status', code // 7 % 2, estimate FROM cell UNION ALL SELECT 'line_no', code % 7, estimate FROM cell) t
GROUP BY attr, code""")
def _(spark, sf):
    v = users(spark, sf, CAT3).withColumn("cell", mix.composite_code(_COLS3))
    cells = est.decode_orthogonal(cat.orthogonal_report(v, "cell", 42, EPS, label="cell"), 42, EPS)
    return mix.marginalise(cells, _COLS3).withColumn("estimate", F.round("estimate", 9))


for _name, _spec in (("mixed", LI23), ("mixed_numeric_only", NUM4), ("mixed_categorical_only", CAT3)):
    if _spec.numerics:

        @query("mixed_means" if _spec is LI23 else _name, O.mixed_means(_spec, EPS))
        def _(spark, sf, spec=_spec):
            return mix.mixed_means(mix.sums(mix.mixed_report(users(spark, sf, spec), spec, EPS)), spec, EPS)

    if _spec.categoricals:

        @query("mixed_frequencies" if _spec is LI23 else _name, O.mixed_frequencies(_spec, EPS))
        def _(spark, sf, spec=_spec):
            return mix.mixed_frequencies(mix.sums(mix.mixed_report(users(spark, sf, spec), spec, EPS)), spec, EPS)


NAMES6 = [a.name for a in NUM6.numerics]


@query("hybrid_means", O.halfspace(users_sql(NUM6), NAMES6, EPS * 6 / 23, "repaired"))
def _(spark, sf):
    numbers, _ = mix.hybrid_report(users(spark, sf, LI23), LI23, EPS, n=1)
    return est.mean_halfspace(numbers, NAMES6, EPS * 6 / 23)


@query("hybrid_frequencies", O.split_frequencies(LI23, EPS, "projection", BETA))
def _(spark, sf):
    v = users(spark, sf, LI23)
    sent = mix.split_report(v, LI23, EPS, n=v.count(), beta=BETA)
    return mix.mixed_frequencies(mix.split_sums(sent), LI23, EPS / 23, oracle="projection", factor=1.0)


@query("freq_postprocessed", f"""
WITH e AS ({O.mixed_frequencies(CAT3, EPS)}), k AS (SELECT attr, code, greatest(0.0::double, least(1.0::double, estimate)) AS x FROM e)
SELECT attr, code, round(x / sum(x) OVER (PARTITION BY attr), 9) AS estimate FROM k""")
def _(spark, sf):
    raw = mix.mixed_frequencies(mix.sums(mix.mixed_report(users(spark, sf, CAT3), CAT3, EPS)), CAT3, EPS)
    return est.project_simplex(raw, ["attr"], "norm").withColumn("estimate", F.round("estimate", 9))


# --- learning -----------------------------------------------------------------------------------

_XS = ["quantity", "discount", "tax"]
_W = [0.1, -0.2, 0.3]
_Y = {"linear": "price", "logistic": "(case when price >= 0 then 1.0::double else -1.0::double end)"}
_Y["svm"] = _Y["logistic"]
_ERM = {k: f"(SELECT ukey, {', '.join(_XS)}, {y} AS y FROM {SRC4} b)" for k, y in _Y.items()}
_SCORE = "(0.0::double" + "".join(f" + {x} * {w!r}::double" for x, w in zip(_XS, _W)) + ")"


def erm(spark: SparkSession, sf: str, kind: str) -> DataFrame:
    y = F.col("price") if kind == "linear" else F.when(F.col("price") >= 0, 1.0).otherwise(-1.0)
    return num4(spark, sf).select("ukey", F.array(*_XS).alias("x"), y.alias("y"))


def weight_rows(spark: SparkSession, w: list[float]) -> DataFrame:
    return lit_table(spark, [(i, float(v)) for i, v in enumerate(w)], "j int, weight double").withColumn("weight", F.round("weight", 9))


@query("erm_objective", "SELECT kind, round(avg(loss), 9) AS risk, round(avg(loss) + 0.00007::double, 9) AS objective FROM (" + " UNION ALL ".join(
    f"SELECT '{k}' AS kind, {x} AS loss FROM {_ERM[k]} v" for k, x in (("linear", f"({_SCORE} - y) ** 2"), ("logistic", f"ln(1 + exp(-y * {_SCORE}))"), ("svm", f"greatest(0.0::double, 1 - y * {_SCORE})"))) + ") t GROUP BY kind")
def _(spark, sf):
    parts = [losses.objective(erm(spark, sf, k), _W, k, 1e-3).select(F.lit(k).alias("kind"), F.round("risk", 9).alias("risk"), F.round("objective", 9).alias("objective")) for k in losses.KINDS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


for _kind in losses.KINDS:
    @query(f"erm_gradient_{_kind}", " UNION ALL ".join(f"SELECT {i} AS j, round(avg({O.slope(_kind, _SCORE, 'y')} * {x}) + {1e-4 * w!r}::double, 9) AS g FROM {_ERM[_kind]} v" for i, (x, w) in enumerate(zip(_XS, _W))))
    def _(spark, sf, kind=_kind):
        g = losses.gradient(kind, F.col("x"), F.col("y"), losses.weights(_W), 1e-4)
        rows = erm(spark, sf, kind).select(F.posexplode(g).alias("j", "g"))
        return rows.groupBy("j").agg(F.round(F.avg("g"), 9).alias("g"))

    # SQL's recursion is too slow for whole tables; a test compares the first steps with it
    @query(f"sgd_exact_{_kind}")
    def _(spark, sf, kind=_kind):
        out = sgd(prepared(erm(spark, sf, kind)), [Model("exact", 3, EPS, 1)], kind, LAM, 1 / 6)
        return out.select("users", F.posexplode("weights").alias("j", "weight")).withColumn("weight", F.round("weight", 9))

    @query(f"sgd_halfspace_{_kind}")
    def _(spark, sf, kind=_kind):
        return sgd(prepared(erm(spark, sf, kind)), [Model("halfspace", 3, EPS, 1)], kind, LAM, mechanism="halfspace")

    @query(f"mgd_{_kind}", O.descent(_ERM[_kind], _XS, _kind, EPS, 4, LAM))
    def _(spark, sf, kind=_kind):
        data = sliced(prepared(erm(spark, sf, kind)))
        return weight_rows(spark, minibatch(data, [Model("mgd", 3, EPS, 4)], kind, LAM)[0].weights)

    @query(f"cv_{_kind}")
    def _(spark, sf, kind=_kind):
        data = erm(spark, sf, kind)
        return cross_validated(data, kind, data.count(), 3, [EPS], folds=10, r=2)


for _mechanism in ("laplace", "one_coordinate"):

    @query(f"sgd_{_mechanism}")
    def _(spark, sf, mechanism=_mechanism):
        return sgd(prepared(erm(spark, sf, "logistic")), [Model(mechanism, 3, EPS, 1)], "logistic", LAM, mechanism=mechanism)


_WIDE_X = ["quantity", "discount", "tax"] + [f"(case when {c.name} = {i} then 1.0::double else -1.0::double end)" for c in CAT3.categoricals for i in range(c.k - 1)]
_SMALL_SQL = f"(SELECT ukey, price, quantity, discount, tax, return_flag, line_status, line_no, price AS y FROM {users_sql(SMALL)} b)"
_P = {s: matrix(4, 12, scale=s) for s in ("one_over_d", "sqrt_r")}


def wide_features(spark: SparkSession, sf: str) -> DataFrame:
    return users(spark, sf, SMALL).select("ukey", features(SMALL, "price").alias("x"), F.col("price").alias("y"))


def _px(scale: str, clip: bool) -> list[str]:
    out = ["(0.0::double" + "".join(f" + {p!r}::double * {x}" for p, x in zip(row, _WIDE_X)) + ")" for row in _P[scale]]
    return [f"greatest(-1.0::double, least(1.0::double, {x}))" for x in out] if clip else out


for _name, _scale, _clip in (("project_features", "one_over_d", False), ("project_features_jl", "sqrt_r", True)):

    @query(_name, " UNION ALL ".join(f"SELECT {i} AS j, round(avg({x}), 9) AS mean, round(max(abs({x})), 9) AS reach FROM {_SMALL_SQL} v" for i, x in enumerate(_px(_scale, _clip))))
    def _(spark, sf, scale=_scale, clip=_clip):
        out = wide_features(spark, sf).select(F.posexplode(project(F.col("x"), _P[scale], clip)).alias("j", "v"))
        return out.groupBy("j").agg(F.round(F.avg("v"), 9).alias("mean"), F.round(F.max(F.abs("v")), 9).alias("reach"))


@query("mgd_projected", O.descent(_SMALL_SQL, _px("one_over_d", False), "linear", EPS, 4, LAM))
def _(spark, sf):
    data = sliced(prepared(wide_features(spark, sf).withColumn("x", project(F.col("x"), _P["one_over_d"]))))
    return weight_rows(spark, minibatch(data, [Model("mgd-p", 4, EPS, 4)], "linear", LAM)[0].weights)


def _participation_sql() -> str:
    """Descent for 1, 2 and 4 participations, each query's weights tested on all users."""
    base, parts = _ERM["logistic"], []
    for m in (1, 2, 4):
        again = f"(SELECT ukey || '#' || turn.range AS ukey, {', '.join(_XS)}, y FROM {base} o, range({m}) turn)"
        trained = O.descent(again, _XS, "logistic", EPS / m, 8 * m, LAM)
        weights = ", ".join(f"max(weight) FILTER (WHERE j = {i}) AS p{i}" for i in range(len(_XS)))
        score = "(0.0::double" + "".join(f" + {x} * p{i}" for i, x in enumerate(_XS)) + ")"
        limit = 3 * math.log(3) * 2 * m * m / EPS**2
        parts.append(f"SELECT {m}::INT AS participations, {O.d(EPS / m)} AS eps_each, {O.d(limit)} AS acceptable_group, {8 * m}::INT AS steps, avg(case when ({score} > 0) = (y > 0) then 0.0::double else 1.0::double end) AS error FROM {base} t, (SELECT {weights} FROM ({trained}) w) p")
    return " UNION ALL ".join(f"({x})" for x in parts)


@query("mgd_participation", _participation_sql())
def _(spark, sf):
    base, rows = erm(spark, sf, "logistic"), []
    for m in (1, 2, 4):
        data = sliced(participating(base, m))
        # the same batch for all: m participations make m times the steps
        model = train(data, [Model("m", 3, EPS / m, 8 * m)], "logistic", LAM)[0]
        error = losses.evaluate(base, losses.weights(model.weights), "logistic").first()["error"]
        rows.append((m, EPS / m, 3 * math.log(3) * 2 * m * m / EPS**2, len(model.history), error))
    return lit_table(spark, rows, "participations int, eps_each double, acceptable_group double, steps int, error double")


def tuples(spark: SparkSession, sf: str) -> int:
    """Line items with a target."""
    return load(spark, sf, "lineitem").agg(F.count("l_extendedprice")).first()[0]


@query("batch_size_grid", """
SELECT dim, eps, g, greatest(1, floor(n / g))::BIGINT AS steps FROM (SELECT dim, eps, n, ceil(greatest(2 * dim * ln(dim) / (eps * eps), n / 1000::double))::BIGINT AS g FROM
  (SELECT unnest([20, 85, 95])::INT AS dim), (SELECT unnest([0.05, 0.1, 0.2, 0.4, 0.8])::double AS eps), (SELECT count(l_extendedprice) AS n FROM lineitem))""")
def _(spark, sf):
    n = tuples(spark, sf)
    # a budget whose batch asks for more users than there are makes one step of all
    rows = [(k, e, C.batch_size(k, e, n), max(1, n // C.batch_size(k, e, n))) for k in (20, 85, 95) for e in ex.EPS_GRID]
    return lit_table(spark, rows, "dim int, eps double, g long, steps long")


@query("one_hot_features", " UNION ALL ".join(f"SELECT {i} AS j, round(avg({x}), 9) AS mean FROM {_SMALL_SQL} v" for i, x in enumerate(_WIDE_X)))
def _(spark, sf):
    return wide_features(spark, sf).select(F.posexplode("x").alias("j", "v")).groupBy("j").agg(F.round(F.avg("v"), 9).alias("mean"))


@query("binary_target", f"WITH v AS (SELECT {NET.sql()} AS y FROM lineitem) SELECT (case when y >= (SELECT avg(y) FROM v) then 1.0 else -1.0 end)::double AS y, count(*) AS n FROM v GROUP BY 1")
def _(spark, sf):
    from ldpspark.plans.schema import binarise_at_mean

    v = load(spark, sf, "lineitem").select(F.expr(NET.sql()).alias("net_price"))
    return binarise_at_mean(v, "net_price").groupBy("y").agg(F.count(F.lit(1)).alias("n"))


# --- measures -----------------------------------------------------------------------------------

_RUNS = 10
_RUN_SRC = f"(SELECT b.*, run.range AS run FROM {SRC4} b, range({_RUNS}) run)"
_RUN_EST = f"""
WITH r AS {O.one_coordinate(_RUN_SRC, NAMES4, EPS, run='run', more='run,')},
e AS (SELECT run, {O.pick('j', [f"'{x}'" for x in NAMES4])} AS attr, {O.d(c1 * 4)} * sum(sign) / (SELECT count(*) FROM lineitem) AS estimate FROM r GROUP BY run, j),
x AS ({ORACLES['exact_means'].replace('round(avg(', '(avg(').replace('), 9)', '))')}),
m AS (SELECT run, max(abs(estimate - exact)) AS linf FROM e JOIN x USING (attr) GROUP BY run)"""


def run_estimates(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    v = stored(num4(spark, sf), "users")
    sent = num.one_coordinate_report(ex.with_runs(v, _RUNS), NAMES4, EPS, run=F.col("run"))
    return mix.mixed_means(mix.sums(sent.withColumn("s", F.lit(None).cast("int")), "run"), NUM4, EPS, "run"), est.exact_mean(v, NAMES4)


@query("runs_averaged", _RUN_EST + f" SELECT 1.0::double AS eps, {_RUNS}::BIGINT AS runs, round(avg(linf), 9) AS mean_linf FROM m")
def _(spark, sf):
    e, x = run_estimates(spark, sf)
    return mea.averaged(mea.linf(e, x, ["attr"], ["run"]).withColumn("eps", F.lit(EPS)), ["eps"]).withColumn("mean_linf", F.round("mean_linf", 9))


@query("bias_check", _RUN_EST + " SELECT attr, count(*) AS runs, round(avg(estimate - exact), 9) AS bias, round(sqrt(avg((estimate - exact) ** 2)), 9) AS rms FROM e JOIN x USING (attr) GROUP BY attr")
def _(spark, sf):
    e, x = run_estimates(spark, sf)
    return mea.bias(e, x, ["attr"]).withColumns({k: F.round(k, 9) for k in ("bias", "rms")})


@query("coverage_check", _RUN_EST + f""" SELECT 1.0::double AS eps, count(*) AS runs, avg(case when linf <= radius then 1.0::double else 0.0::double end) AS covered FROM m,
  (SELECT (b * l + sqrt(b * b * l * l + 4 * n * a * l)) / (2 * n) AS radius FROM (SELECT count(*) AS n, ln(8 / 0.05::double) AS l, {O.d(8 * c1 * c1)} AS a, {O.d(16 / 3 * c1)} AS b FROM lineitem))""")
def _(spark, sf):
    e, x = run_estimates(spark, sf)
    radius = C.mean_radius(load(spark, sf, "lineitem").count(), 4, EPS, BETA)
    return mea.coverage(mea.linf(e, x, ["attr"], ["run"]).withColumn("eps", F.lit(EPS)), radius, ["eps"])


@query("linf_means", f"WITH e AS ({O.mixed_means(NUM4, EPS)}), x AS ({ORACLES['exact_means'].replace('round(avg(', '(avg(').replace('), 9)', '))')}) SELECT 'mixed' AS method, round(max(abs(estimate - exact)), 9) AS linf FROM e JOIN x USING (attr)")
def _(spark, sf):
    v = num4(spark, sf)
    e = mix.mixed_means(mix.sums(mix.mixed_report(v, NUM4, EPS)), NUM4, EPS).withColumn("method", F.lit("mixed"))
    return mea.linf(e, est.exact_mean(v, NAMES4), ["attr"], ["method"]).withColumn("linf", F.round("linf", 9))


@query("linf_frequencies", f"WITH e AS ({O.mixed_frequencies(CAT3, EPS)}), x AS ({O.histogram(SRC3, _COLS3)}) SELECT attr, round(max(abs(estimate - exact)), 9) AS linf FROM e JOIN x USING (attr, code) GROUP BY attr")
def _(spark, sf):
    v = users(spark, sf, CAT3)
    e = mix.mixed_frequencies(mix.sums(mix.mixed_report(v, CAT3, EPS)), CAT3, EPS)
    return mea.linf(e, est.exact_histogram(v, _COLS3), ["attr", "code"], ["attr"]).withColumn("linf", F.round("linf", 9))


_K23 = tuple(x.k for x in LI23.categoricals)


@query("communication_cost", "SELECT method, bits, n AS users, bits * n AS total FROM (VALUES ('laplace', 1472.0::double), ('half_space', 23.0::double), ('one_coordinate', 1.0::double), ('mixed', 1.0::double), ('hybrid', 23.0::double)) t(method, bits), (SELECT count(l_extendedprice) AS n FROM lineitem)")
def _(spark, sf):
    n = tuples(spark, sf)
    bits = [(m, float(num.bits_per_user(m, 23, _K23))) for m in ("laplace", "half_space", "one_coordinate", "mixed", "hybrid")]
    return lit_table(spark, [(m, b, n, b * n) for m, b in bits], "method string, bits double, users long, total double")


# --- workloads ----------------------------------------------------------------------------------

def lines(spark: SparkSession, sf: str) -> int:
    return load(spark, sf, "lineitem").count()


def named_grid(found: DataFrame, n: int, study: str) -> DataFrame:
    """Adds which of the two grids a budget belongs to."""
    names = found.sparkSession.createDataFrame(ex.both_grids(n, study), "grid string, eps double")
    return found.join(F.broadcast(names), "eps")


for _name, _spec in (("w1_freq_wide", LI23), ("w2_freq_narrow", LI18)):

    @query(_name)
    def _(spark, sf, spec=_spec):
        n = lines(spark, sf)
        return named_grid(ex.frequency_errors(spark, sf, spec, [e for _, e in ex.both_grids(n, spec.name)]), n, spec.name)


for _name, _spec in (("w3_mean_wide", LI23), ("w4_mean_narrow", LI18)):

    @query(_name)
    def _(spark, sf, spec=_spec):
        n = lines(spark, sf)
        return named_grid(ex.mean_errors(spark, sf, spec, [e for _, e in ex.both_grids(n, spec.name)], readings=("mixed", "numeric_only")), n, spec.name)


_STUDIES = [("w5_linear_wide", LI23, "linear"), ("w6_logistic_wide", LI23, "logistic"), ("w7_svm_wide", LI23, "svm"), ("w8_linear_narrow", LI18, "linear"), ("w9_logistic_narrow", LI18, "logistic"), ("w10_svm_narrow", LI18, "svm")]
for _name, _spec, _kind in _STUDIES:

    @query(_name)
    def _(spark, sf, spec=_spec, kind=_kind):
        n = lines(spark, sf)
        data = ex.learning_view(spark, sf, spec, kind)
        grid = [e for _, e in ex.both_grids(n, spec.name)]
        found = cross_validated(data, kind, n, spec.one_hot_dimension, grid, ex.FOLDS, ex.LAMBDA, ex.REDUCED)
        exact = found.where("method = 'sgd_exact'").withColumn("grid", F.lit("none"))
        return named_grid(found.where("method != 'sgd_exact'"), n, spec.name).unionByName(exact)


_TYPES = ("click", "error", "purchase", "signup", "view")
_TYPE_CODE = "(case event_type " + " ".join(f"when '{t}' then {i}" for i, t in enumerate(_TYPES)) + " end)"


def snapshots(spark: SparkSession, sf: str) -> DataFrame:
    """First event of each user in each week, as a tuple of one number and two categories."""
    e = stream.timed(load(spark, sf, "events")).withColumn("period", F.floor(F.unix_seconds("ts") / 604800).cast("long"))
    first = relops.first_per_user(e, ["user_id", "period"], ["ts", "event_id"])
    key = F.concat_ws("|", F.col("user_id").cast("string"), F.col("period").cast("string"))
    return first.select("period", key.alias("ukey"), F.expr("(2 * (least(greatest(value, 0.0D), 600.0D) - 0.0D) / 600.0D - 1)").alias("value"), F.expr(_TYPE_CODE).alias("event_type"), F.from_json("props", "k int")["k"].alias("k"))


@query("w12_event_snapshots", f"""
WITH f AS (SELECT * FROM (SELECT *, floor(epoch(ts) / 604800)::BIGINT AS period, row_number() OVER (PARTITION BY user_id, floor(epoch(ts) / 604800) ORDER BY ts, event_id) AS nth FROM events) WHERE nth = 1),
v AS (SELECT period, user_id::varchar || '|' || period::varchar AS ukey, 2 * (least(greatest(value, 0.0::double), 600.0::double) - 0.0::double) / 600.0::double - 1 AS value, {_TYPE_CODE} AS event_type, (props->>'k')::INT AS k FROM f),
q AS (SELECT *, case when j = 1 then floor({u('ukey', 'row')} * 8)::INT when j = 2 then floor({u('ukey', 'row')} * 128)::INT end AS s FROM (SELECT *, floor({u('ukey', 'attr')} * 3)::INT AS j, {u('ukey', 'toss')} AS ut FROM v) z),
r AS (SELECT period, j, s, case when j = 0 then {O.toss('value', EPS, 'ut')} else (1 - 2 * (bit_count((s & (case j when 1 then event_type else k end))::BIGINT) % 2)) * (case when ut < {O.d(C.keep_probability(EPS))} then 1 else -1 end) end AS sign FROM q),
n AS (SELECT period, count(*) AS n FROM r GROUP BY period),
t AS (SELECT period, j, s, sum(sign)::BIGINT AS total FROM r GROUP BY period, j, s)
SELECT period, attr, code, {O.d(c1 * 3)} * dot / n AS estimate FROM (
  SELECT period, 'value' AS attr, -1 AS code, sum(total) AS dot FROM t WHERE j = 0 GROUP BY period
  UNION ALL SELECT period, 'event_type', code, sum(total * (1 - 2 * (bit_count((s & code)::BIGINT) % 2))) FROM t, (SELECT range::INT AS code FROM range(5)) WHERE j = 1 GROUP BY period, code
  UNION ALL SELECT period, 'k', code, sum(total * (1 - 2 * (bit_count((s & code)::BIGINT) % 2))) FROM t, (SELECT range::INT AS code FROM range(100)) WHERE j = 2 GROUP BY period, code) JOIN n USING (period)""")
def _(spark, sf):
    from ldpspark.plans.schema import Categorical, Numeric

    spec = TupleSpec("events", (Numeric("value", "value", 0.0, 600.0),), (Categorical("event_type", "event_type", 5), Categorical("k", "k", 100)), ("user_id",))
    data = snapshots(spark, sf)
    sent = mix.mixed_report(data.withColumn("run", F.col("period")), spec, EPS)
    totals = stored(mix.sums(sent, "run"), "totals")
    means = mix.mixed_means(totals, spec, EPS, "run").withColumn("code", F.lit(-1))
    return means.unionByName(mix.mixed_frequencies(totals, spec, EPS, "run")).select(F.col("run").alias("period"), "attr", "code", "estimate")


@query("w13_error_model")
def _(spark, sf):
    e = stream.timed(load(spark, sf, "events"))
    x = F.array(F.expr("(2 * (least(greatest(value, 0.0D), 600.0D)) / 600.0D - 1)"), 2 * F.from_json("props", "k int")["k"] / 99 - 1, 2 * F.hour("ts") / 23 - 1, F.lit(1.0))
    data = sliced(prepared(e.select(F.col("event_id").cast("string").alias("ukey"), x.alias("x"), F.when(F.col("event_type") == "error", 1.0).otherwise(-1.0).alias("y")), 10))
    models = train(data, [Model(str(f), 4, EPS, 16, f) for f in range(10)], "logistic", LAM)
    weights = lit_table(spark, [(m.name, m.fold, m.weights) for m in models], "model string, mfold int, w array<double>")
    from ldpspark.erm.crossval import tested

    return tested(data, weights, "logistic")


_SWEEP_DIMS = [1, 2, 4, 8, 16, 32, 64]


@query("w14_dimension_sweep", O.dimension_errors("(SELECT vec_id::varchar AS ukey, embedding::DOUBLE[] AS x FROM embeddings)", _SWEEP_DIMS, EPS, 10))
def _(spark, sf):
    return ex.dimension_sweep(spark, sf, _SWEEP_DIMS, EPS, 10, mode="md5").withColumn("rms", F.round("rms", 9))


_HOST_SQL = "cast('0x' || substr(md5(regexp_extract(url, '://([^/?#]*)', 1)), 1, 13) AS BIGINT) % 64"
_DOMAINS = [
    ("lang", 4, "(SELECT doc_id::varchar AS ukey, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS v FROM documents)"),
    ("source", 20, "(SELECT doc_id::varchar AS ukey, substr(source, 4)::INT AS v FROM documents)"),
    ("host", 64, f"(SELECT page_id::varchar AS ukey, {_HOST_SQL} AS v FROM pages)"),
    ("k", 100, "(SELECT event_id::varchar AS ukey, (props->>'k')::INT AS v FROM events)"),
]


@query("w15_domain_sweep", " UNION ALL ".join(O.domain_errors(source, label, k, EPS, BETA, 10) for label, k, source in _DOMAINS))
def _(spark, sf):
    docs = load(spark, sf, "documents")
    lang = F.array_position(F.array(*[F.lit(x) for x in ("de", "en", "es", "fr")]), F.col("lang")).cast("int") - 1
    source = F.substring("source", 4, 10).cast("int")
    d = stored(docs.select(F.col("doc_id").cast("string").alias("ukey"), lang.alias("lang"), source.alias("source")), "docs")
    e = stored(load(spark, sf, "events").select(F.col("event_id").cast("string").alias("ukey"), F.from_json("props", "k int")["k"].alias("k")), "events")
    host = F.regexp_extract("url", "://([^/?#]*)", 1)
    p = stored(load(spark, sf, "pages").select(F.col("page_id").cast("string").alias("ukey"), (F.conv(F.substring(F.md5(host), 1, 13), 16, 10).cast("long") % 64).cast("int").alias("host")), "pages")
    sweep = lambda data, columns: ex.domain_sweep(data, columns, EPS, 10, mode="md5")
    out = sweep(d, [("lang", "lang", 4), ("source", "source", 20)]).unionByName(sweep(p, [("host", "host", 64)])).unionByName(sweep(e, [("k", "k", 100)]))
    return out.withColumn("rms", F.round("rms", 9))


@query("w16_participation")
def _(spark, sf):
    base = stored(ex.learning_view(spark, sf, LI23, "logistic"), "features")
    rows = []
    n = base.count()
    for m in (1, 2, 4):
        eps = 4.0 / m
        g = C.batch_size(85, eps, n)
        model = Model("m", 85, eps, max(1, n * m // g))
        data = participating(base, m, mode="xx")
        # only steps by jobs read slices
        data = sliced(data) if n * m / model.steps >= STREAMED else data
        model = train(data, [model], "logistic", LAM)[0]
        error = losses.evaluate(base, losses.weights(model.weights), "logistic").first()["error"]
        rows.append((m, eps, g, len(model.history), error))
    return lit_table(spark, rows, "participations int, eps_each double, g long, steps int, error double")


# --- around the collection ----------------------------------------------------------------------

@query("scan_profile", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def _(spark, sf):
    out = None
    for t in TABLES:
        one = load(spark, sf, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("normalised_numeric", "WITH v AS (SELECT * FROM " + SRC4 + " s) " + " UNION ALL ".join(f"SELECT '{n}' AS attr, round(min({n}), 9) AS low, round(max({n}), 9) AS high FROM v" for n in NAMES4))
def _(spark, sf):
    v = num4(spark, sf).select(F.explode(F.array(*[F.struct(F.lit(n).alias("attr"), F.col(n).alias("v")) for n in NAMES4])).alias("x")).select("x.*")
    return v.groupBy("attr").agg(F.round(F.min("v"), 9).alias("low"), F.round(F.max("v"), 9).alias("high"))


@query("encoded_categories", "WITH v AS (SELECT * FROM " + users_sql(LI18) + " s) " + " UNION ALL ".join(f"SELECT '{x.name}' AS attr, {x.name} AS code, count(*) AS n FROM v GROUP BY {x.name}" for x in LI18.categoricals))
def _(spark, sf):
    pairs = F.array(*[F.struct(F.lit(x.name).alias("attr"), F.col(x.name).alias("code")) for x in LI18.categoricals])
    return users(spark, sf, LI18).select(F.explode(pairs).alias("x")).groupBy("x.attr", "x.code").agg(F.count(F.lit(1)).alias("n"))


@query("wide_view_counts", f"SELECT c_mktsegment, o_orderstatus, cn_regionkey, count(*) AS n FROM {WIDE_SQL} w GROUP BY ALL")
def _(spark, sf):
    return wide(spark, sf).groupBy("c_mktsegment", "o_orderstatus", "cn_regionkey").agg(F.count(F.lit(1)).alias("n"))


@query("reported_users", "SELECT c_custkey, c_mktsegment FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")
def _(spark, sf):
    return load(spark, sf, "customer").join(load(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", "c_mktsegment")


@query("silent_users", "SELECT c_custkey, c_mktsegment FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderpriority = '1-URGENT')")
def _(spark, sf):
    urgent = load(spark, sf, "orders").where(F.col("o_orderpriority") == "1-URGENT")
    return load(spark, sf, "customer").join(urgent, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey", "c_mktsegment")


_BANDS = [(0, 0, 100), (1, 100, 1000), (2, 1000, 10000), (3, 10000, 10**12)]


@query("band_join", "SELECT band, count(*) AS n FROM documents JOIN (VALUES " + ", ".join(str(b) for b in _BANDS) + ") b(band, lo, hi) ON n_chars >= lo AND n_chars < hi GROUP BY band")
def _(spark, sf):
    bands = lit_table(spark, _BANDS, "band int, lo long, hi long")
    return relops.band_join(load(spark, sf, "documents").select("n_chars"), "n_chars", bands).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@query("asof_model", """
WITH m AS (SELECT user_id, ts, value AS model FROM events WHERE event_type = 'view' QUALIFY row_number() OVER (PARTITION BY user_id, ts ORDER BY event_id) = 1),
a AS (SELECT user_id, ts, event_id FROM events WHERE event_type = 'error')
SELECT a.user_id, a.event_id, m.model FROM a ASOF LEFT JOIN m ON a.user_id = m.user_id AND a.ts >= m.ts""")
def _(spark, sf):
    e = stream.timed(load(spark, sf, "events"))
    seen = relops.first_per_user(e.where("event_type = 'view'").select("user_id", "ts", "event_id", "value"), ["user_id", "ts"], ["event_id"])
    arrivals = e.where("event_type = 'error'").select("user_id", "ts", "event_id")
    out = relops.asof_join(arrivals, seen.select("user_id", "ts", F.col("value").alias("model")), "ts", ["user_id"], ["model"], F.to_date("ts"))
    return out.select("user_id", "event_id", "model")


_STRATA_SQL = f"(SELECT return_flag, line_status, case when {u('ukey', 'toss')} < {O.d(C.keep_probability(EPS))} then 1 else -1 end * (case when line_no >= 3 then 1 else -1 end) AS sign FROM {SRC3} b)"


def strata(spark: SparkSession, sf: str) -> DataFrame:
    keep = F.when(uniform("ukey", "toss") < C.keep_probability(EPS), 1).otherwise(-1)
    return users(spark, sf, CAT3).select("return_flag", "line_status", (keep * F.when(F.col("line_no") >= 3, 1).otherwise(-1)).alias("sign"))


_LEVELS = "coalesce(return_flag::varchar, 'all') AS return_flag, coalesce(line_status::varchar, 'all') AS line_status"
_AGG = f"{O.d(c1)} * sum(sign) / count(*) AS estimate, count(*) AS n"


def _strata_agg(grouped) -> DataFrame:
    out = grouped.agg((F.lit(c1) * F.sum("sign") / F.count(F.lit(1))).alias("estimate"), F.count(F.lit(1)).alias("n"))
    return out.withColumns({x: F.coalesce(F.col(x).cast("string"), F.lit("all")) for x in ("return_flag", "line_status")})


@query("strata_rollup", f"SELECT {_LEVELS}, {_AGG} FROM {_STRATA_SQL} t GROUP BY ROLLUP (return_flag, line_status)")
def _(spark, sf):
    return _strata_agg(strata(spark, sf).rollup("return_flag", "line_status"))


@query("strata_cube", f"SELECT {_LEVELS}, {_AGG} FROM {_STRATA_SQL} t GROUP BY CUBE (return_flag, line_status)")
def _(spark, sf):
    return _strata_agg(strata(spark, sf).cube("return_flag", "line_status"))


@query("strata_grouping_sets", f"SELECT {_LEVELS}, {_AGG} FROM {_STRATA_SQL} t GROUP BY GROUPING SETS ((return_flag), (line_status))")
def _(spark, sf):
    return _strata_agg(strata(spark, sf).groupingSets([["return_flag"], ["line_status"]], "return_flag", "line_status"))


@query("first_report_per_user", "SELECT user_id, event_id, value FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nth FROM events) t WHERE nth = 1")
def _(spark, sf):
    return relops.first_per_user(load(spark, sf, "events").select("user_id", "ts", "event_id", "value"), ["user_id"], ["ts", "event_id"]).select("user_id", "event_id", "value")


@query("batch_assignment", f"SELECT c_custkey, ((row_number() OVER (ORDER BY {u('c_custkey::varchar', 'batch')}) - 1) // 100)::INT AS batch FROM customer")
def _(spark, sf):
    v = load(spark, sf, "customer").select("c_custkey", F.col("c_custkey").cast("string").alias("ukey"))
    return relops.batches(v, uniform("ukey", "batch"), 100).select("c_custkey", "batch")


@query("running_budget", "SELECT event_id, user_id, 0.25::double * count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS spent_so_far FROM events")
def _(spark, sf):
    e = load(spark, sf, "events").select("event_id", "user_id", "ts", F.lit(0.25).alias("eps"))
    return budget.running(e, "user_id", ["ts", "event_id"]).select("event_id", "user_id", "spent_so_far")


@query("alpha_change", f"""
WITH t AS ({_RUN_EST} SELECT * FROM e)
SELECT run, attr, round(abs(estimate - lag(estimate) OVER (PARTITION BY attr ORDER BY run)), 9) AS moved FROM t""")
def _(spark, sf):
    e, _ = run_estimates(spark, sf)
    return e.select(F.col("run").cast("long").alias("run"), "attr", F.round(F.abs(F.col("estimate") - F.lag("estimate").over(Window.partitionBy("attr").orderBy("run"))), 9).alias("moved"))


@query("top_values", f"SELECT * FROM ({O.mixed_frequencies(CAT3, EPS)}) ORDER BY estimate DESC, attr, code LIMIT 5")
def _(spark, sf):
    e = mix.mixed_frequencies(mix.sums(mix.mixed_report(users(spark, sf, CAT3), CAT3, EPS)), CAT3, EPS)
    return relops.top_values(e, 5)


@query("domain_gap", "SELECT 'unseen' AS side, code FROM (SELECT range::INT AS code FROM range(50) EXCEPT SELECT l_quantity::INT - 1 FROM lineitem WHERE l_linenumber = 7 AND l_tax > 0.05) UNION ALL SELECT 'outside', code FROM (SELECT l_quantity::INT - 1 AS code FROM lineitem EXCEPT SELECT range::INT FROM range(40))")
def _(spark, sf):
    line = load(spark, sf, "lineitem")
    code = (F.col("l_quantity").cast("int") - 1).alias("code")
    domain = lambda k: spark.range(k).select(F.col("id").cast("int").alias("code"))
    unseen = domain(50).exceptAll(line.where("l_linenumber = 7 and l_tax > 0.05").select(code).distinct())
    outside = line.select(code).distinct().exceptAll(domain(40))
    return unseen.select(F.lit("unseen").alias("side"), "code").unionByName(outside.select(F.lit("outside").alias("side"), "code"))


@query("estimate_union", f"SELECT attr, -1 AS code, estimate FROM ({O.mixed_means(SMALL, EPS)}) a UNION ALL SELECT attr, code, estimate FROM ({O.mixed_frequencies(SMALL, EPS)}) b")
def _(spark, sf):
    t = mix.sums(mix.mixed_report(users(spark, sf, SMALL), SMALL, EPS))
    return mix.mixed_means(t, SMALL, EPS).withColumn("code", F.lit(-1)).unionByName(mix.mixed_frequencies(t, SMALL, EPS))


@query("page_hosts", "SELECT cast('0x' || substr(md5(regexp_extract(url, '://([^/?#]*)', 1)), 1, 13) AS BIGINT) % 64 AS bucket, count(*) AS n FROM pages GROUP BY 1")
def _(spark, sf):
    host = F.regexp_extract("url", "://([^/?#]*)", 1)
    return load(spark, sf, "pages").groupBy((F.conv(F.substring(F.md5(host), 1, 13), 16, 10).cast("long") % 64).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@query("event_props", "SELECT (props->>'k')::INT AS k, event_type, count(*) AS n FROM events GROUP BY ALL")
def _(spark, sf):
    return load(spark, sf, "events").groupBy(F.from_json("props", "k int")["k"].alias("k"), "event_type").agg(F.count(F.lit(1)).alias("n"))


@query("date_parts", "SELECT month(o_orderdate)::INT AS month, dayofweek(o_orderdate)::INT AS weekday, count(*) AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::INT AS days FROM orders GROUP BY ALL")
def _(spark, sf):
    return load(spark, sf, "orders").groupBy(F.month("o_orderdate").alias("month"), (F.dayofweek("o_orderdate") - 1).alias("weekday")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff("o_orderdate", F.lit("1992-01-01").cast("date"))).alias("days"))


@query("tuple_unpivot", "WITH v AS (SELECT * FROM " + SRC4 + " s) " + " UNION ALL ".join(f"SELECT '{n}' AS attr, count(*) AS n, round(sum({n}), 6) AS total FROM v" for n in NAMES4))
def _(spark, sf):
    long = num4(spark, sf).unpivot("ukey", NAMES4, "attr", "value")
    return long.groupBy("attr").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 6).alias("total"))


def event_signs(spark: SparkSession, sf: str) -> DataFrame:
    e = stream.timed(load(spark, sf, "events"))
    sign = F.when(uniform(F.col("event_id").cast("string"), "toss") < C.keep_probability(EPS), 1).otherwise(-1) * F.when(F.col("event_type") == "error", 1).otherwise(-1)
    return e.select("user_id", "ts", F.lit(0).alias("j"), sign.alias("sign"))


_ESIGN = f"(SELECT user_id, ts, case when {u('event_id::varchar', 'toss')} < {O.d(C.keep_probability(EPS))} then 1 else -1 end * (case when event_type = 'error' then 1 else -1 end) AS sign FROM events)"


@query("window_tumbling", f"SELECT (floor(epoch(ts) / 604800) * 604800)::BIGINT AS start, 0 AS j, sum(sign)::BIGINT AS total, count(*) AS reports FROM {_ESIGN} e GROUP BY 1")
def _(spark, sf):
    return stream.tumbling(event_signs(spark, sf), "7 days").withColumn("start", F.unix_seconds("start"))


@query("window_sliding", f"""
SELECT (start * 86400)::BIGINT AS start, 0 AS j, sum(sign)::BIGINT AS total, count(*) AS reports FROM (
  SELECT sign, unnest(range(floor(epoch(ts) / 86400)::BIGINT - 6, floor(epoch(ts) / 86400)::BIGINT + 1)) AS start FROM {_ESIGN} e) t GROUP BY start""")
def _(spark, sf):
    return stream.sliding(event_signs(spark, sf), "7 days", "1 day").withColumn("start", F.unix_seconds("start"))


@query("window_session", """
WITH g AS (SELECT *, case when epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 43200000000 then 0 else 1 end AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM g)
SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM s GROUP BY user_id, session""")
def _(spark, sf):
    return stream.sessions(stream.timed(load(spark, sf, "events")), "user_id", "12 hours").select("user_id", F.unix_micros("start").alias("start"), "n")


@query("sql_surface", f"""
WITH r AS (SELECT s, (1 - 2 * (bit_count((s & line_no)::BIGINT) % 2)) * (case when {u('ukey', 'flip')} < 1 / (1 + exp(-1.0::double)) then 1 else -1 end) AS sign FROM (SELECT *, floor({u('ukey', 'row')} * 8)::INT AS s FROM {SRC3} b) z),
t AS (SELECT s, sum(sign)::BIGINT AS total FROM r GROUP BY s)
SELECT code, sum(total * (1 - 2 * (bit_count((s & code)::BIGINT) % 2)))::BIGINT AS dot FROM t, (SELECT range::INT AS code FROM range(8)) GROUP BY code""")
def _(spark, sf):
    sqlfuncs.register(spark)
    users(spark, sf, CAT3).createOrReplaceTempView("ldp_users")
    return spark.sql("""
        SELECT d.code, d.dot FROM ldp_decode(TABLE(
          SELECT s, sum(ldp_orthogonal(ukey, s, line_no, 1.0D, 42)) AS total, 8 AS k
          FROM (SELECT ukey, line_no, cast(floor(ldp_uniform(ukey, 'row', 42) * 8) AS INT) AS s FROM ldp_users) GROUP BY s) WITH SINGLE PARTITION) d""")
