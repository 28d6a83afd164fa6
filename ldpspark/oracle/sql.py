"""SQL builders. Reports are replayed row by row from the keyed draws."""

from __future__ import annotations

import math

from ldpspark.functions import constants as C
from ldpspark.functions.rng import uniform_sql as u
from ldpspark.plans.schema import TupleSpec
from ldpspark.plans.views import users_sql


def d(x: float) -> str:
    return f"cast('{x!r}' as double)"


def pick(j: str, values: list[str], first: int = 0) -> str:
    return f"(case {j} " + " ".join(f"when {first + i} then {v}" for i, v in enumerate(values)) + " end)"


def toss(value: str, eps: float, draw: str) -> str:
    return f"(case when {draw} < ({value}) * {d(1 / (2 * C.report_scale(eps)))} + 0.5::double then 1 else -1 end)"


def one_coordinate(source: str, names: list[str], eps: float, run: str = "0", public: bool = False, more: str = "") -> str:
    """(more, ukey, j, sign)."""
    n = len(names)
    j = u("ukey", "public", 0) if public else u("ukey", "attr", run=run)
    return f"(SELECT {more} ukey, j, {toss(pick('j', names), eps, u('ukey', 'toss', run=run))} AS sign FROM (SELECT *, floor({j} * {n})::INT AS j FROM {source} s0) s1)"


def mean_sparse(reports: str, names: list[str], eps: float, cohort: bool = False) -> str:
    c = C.report_scale(eps)
    value = f"{d(c)} * total / reports" if cohort else f"{d(c * len(names))} * total / n"
    quoted = [f"'{x}'" for x in names]
    return f"SELECT j, {pick('j', quoted)} AS attr, {value} AS estimate FROM (SELECT j, sum(sign)::BIGINT AS total, count(*) AS reports, sum(count(*)) OVER ()::BIGINT AS n FROM {reports} r GROUP BY j) t"


def halfspace(source: str, names: list[str], eps: float, variant: str, total_eps: float | None = None) -> str:
    """(attr, estimate): long form, one row per user and attribute, places ranked by a window."""
    n = len(names)
    inside, other = C.halfspace_cdf(n)
    places = lambda cdf: " + ".join(f"(case when {u('ukey', 'agree')} >= {d(x)} then 1 else 0 end)" for x in cdf[:-1])
    rows = " UNION ALL ".join(
        f"SELECT ukey, '{x}' AS attr, case when {u('ukey', f'round:{x}')} < ({x} + 1) / 2 then 1 else -1 end AS v, {u('ukey', f'subset:{x}')} AS r FROM v" for x in names
    )
    return f"""
WITH v AS (SELECT * FROM {source} s0),
a AS (SELECT ukey, case when {u('ukey', 'side')} < {d(C.halfspace_prob(n, eps, variant))} then {places(inside)} else {places(other)} end AS a FROM v),
l AS ({rows}),
k AS (SELECT l.*, a.a, row_number() OVER (PARTITION BY ukey ORDER BY r) AS nth FROM l JOIN a USING (ukey))
SELECT attr, {d(C.halfspace_scale(n, eps))} * sum(case when nth <= a then v else -v end) / count(*) AS estimate FROM k GROUP BY attr"""


def orthogonal(source: str, column: str, k: int, eps: float, label: str = "") -> str:
    """(code, estimate) of the orthogonal oracle."""
    order = C.orthogonal_order(k)
    return f"""
WITH r AS (SELECT s, (1 - 2 * (bit_count((s & {column})::BIGINT) % 2)) * (case when {u('ukey', f'flip{label}')} < {d(C.keep_probability(eps))} then 1 else -1 end) AS sign
           FROM (SELECT *, floor({u('ukey', f'row{label}')} * {order})::INT AS s FROM {source} s0) s1),
t AS (SELECT s, sum(sign)::BIGINT AS total, count(*) AS n FROM r GROUP BY s),
l AS (SELECT range::INT AS code FROM range({k}))
SELECT code, {d(C.report_scale(eps))} * sum(total * (1 - 2 * (bit_count((s & code)::BIGINT) % 2))) / sum(n) AS estimate FROM t, l GROUP BY code"""


def mixed_reports(spec: TupleSpec, eps: float, run: str = "0", source: str | None = None, more: str = "") -> str:
    """(more, j, s, sign) of the one-attribute sampler with the orthogonal oracle."""
    names = [a.name for a in spec.numerics]
    cats = [c.name for c in spec.categoricals]
    number = toss(pick("j", names), eps, "ut") if names else "NULL"
    flip = f"(case when ut < {d(C.keep_probability(eps))} then 1 else -1 end)"
    code = pick("j", cats, spec.dn) if cats else "NULL"
    size = pick("j", [str(C.orthogonal_order(c.k)) for c in spec.categoricals], spec.dn) if cats else "NULL"
    sign = f"(1 - 2 * (bit_count((s & {code})::BIGINT) % 2)) * {flip}" if cats else "NULL"
    return f"""(SELECT {more} j, s, case when j < {spec.dn} then {number} else {sign} end AS sign FROM (
  SELECT *, case when j >= {spec.dn} then floor({u('ukey', 'row', run=run)} * {size})::INT end AS s FROM (
    SELECT *, floor({u('ukey', 'attr', run=run)} * {spec.d})::INT AS j, {u('ukey', 'toss', run=run)} AS ut FROM {source or users_sql(spec)} s0) s1) s2)"""


def mixed_means(spec: TupleSpec, eps: float) -> str:
    names = [f"'{a.name}'" for a in spec.numerics]
    return f"""
WITH r AS {mixed_reports(spec, eps)}
SELECT {pick('j', names)} AS attr, {d(C.report_scale(eps) * spec.d)} * sum(sign) / (SELECT count(*) FROM r) AS estimate FROM r WHERE j < {spec.dn} GROUP BY j"""


def domain(spec: TupleSpec) -> str:
    return "(VALUES " + ", ".join(f"({j}, '{n}', {v})" for j, n, _, v in spec.domain()) + ") dom(j, attr, code)"


def mixed_frequencies(spec: TupleSpec, eps: float) -> str:
    return f"""
WITH r AS {mixed_reports(spec, eps)},
t AS (SELECT j, s, sum(sign)::BIGINT AS total FROM r WHERE j >= {spec.dn} GROUP BY j, s)
SELECT attr, code, {d(C.report_scale(eps) * spec.d)} * sum(total * (1 - 2 * (bit_count((s & code)::BIGINT) % 2))) / (SELECT count(*) FROM r) AS estimate
FROM t JOIN {domain(spec)} USING (j) GROUP BY attr, code"""


def projection_rows(k: int, eps: float, beta: float, n: str) -> str:
    """Rows of the random matrix for ``n`` users, an SQL expression."""
    return f"greatest(1, ceil({d(math.log(k + 1) * math.log(2 / beta))} / ({d(math.log(2 * k / beta))} / ({d(eps * eps)} * {n}))))::BIGINT"


def split_frequencies(spec: TupleSpec, eps: float, oracle: str, beta: float = 0.05) -> str:
    """(attr, code, estimate) with the budget split over all attributes."""
    part = eps / spec.d
    rows = lambda k: C.orthogonal_order(k) if oracle == "orthogonal" else projection_rows(k, part, beta, "users")
    long = " UNION ALL ".join(f"SELECT ukey || '|{spec.dn + i}' AS key, {spec.dn + i} AS j, {rows(c.k)} AS m, {c.name} AS v FROM base, (SELECT count(*) AS users FROM base)" for i, c in enumerate(spec.categoricals))
    if oracle == "orthogonal":
        sign = lambda v: f"(1 - 2 * (bit_count((s & {v})::BIGINT) % 2))"
    else:
        cell = lambda v: f"(j::varchar || '/' || s::varchar || '|' || {v}::varchar)"
        sign = lambda v: f"(case when {u(cell(v), 'phi:m')} < 0.5 then 1 else -1 end)"
    return f"""
WITH base AS (SELECT * FROM {users_sql(spec)} s0), l AS ({long}),
r AS (SELECT j, s, {sign('v')} * (case when {u('key', 'flip')} < {d(C.keep_probability(part))} then 1 else -1 end) AS sign FROM (SELECT *, floor({u('key', 'row')} * m)::INT AS s FROM l) x),
t AS (SELECT j, s, sum(sign)::BIGINT AS total, count(*) AS c FROM r GROUP BY j, s),
n AS (SELECT j, sum(c)::BIGINT AS n FROM t GROUP BY j)
SELECT attr, code, {d(C.report_scale(part))} * sum(total * {sign('code')}) / any_value(n) AS estimate FROM t JOIN n USING (j) JOIN {domain(spec)} USING (j) GROUP BY attr, code"""


def histogram(source: str, columns: list[tuple[str, int]]) -> str:
    parts = " UNION ALL ".join(f"SELECT '{n}' AS attr, range::INT AS code, (SELECT count(*) FROM v WHERE {n} = range) / (SELECT count(*) FROM v)::double AS exact FROM range({k})" for n, k in columns)
    return f"WITH v AS (SELECT * FROM {source} s0) {parts}"


def domain_errors(source: str, label: str, k: int, eps: float, beta: float, runs: int) -> str:
    """(attr, k, oracle, m, rms) of both oracles over several runs: ``source`` gives ukey and the code v."""

    def part(oracle: str) -> str:
        if oracle == "orthogonal":
            rows = str(C.orthogonal_order(k))
            sign = lambda v: f"(1 - 2 * (bit_count((s & {v})::BIGINT) % 2))"
        else:
            rows = projection_rows(k, eps, beta, "users")
            sign = lambda v: f"(case when {u(f'(s::varchar || chr(124) || {v}::varchar)', f'phi:{label}')} < 0.5 then 1 else -1 end)"
        return f"""
SELECT '{label}' AS attr, {k} AS k, '{oracle}' AS oracle, any_value(m)::INT AS m, round(sqrt(avg((estimate - exact) * (estimate - exact))), 9) AS rms FROM (
  SELECT run, code, any_value(m) AS m, {d(C.report_scale(eps))} * sum(total * {sign('code')}) / sum(reports) AS estimate FROM (
    SELECT run, s, any_value(m) AS m, sum(sign)::BIGINT AS total, count(*) AS reports FROM (
      SELECT run, m, s, {sign('v')} * (case when {u('ukey', f'flip{label}')} < {d(C.keep_probability(eps))} then 1 else -1 end) AS sign FROM (
        SELECT *, floor({u('ukey', f'row{label}')} * m)::INT AS s FROM (
          SELECT ukey || '~' || run::varchar AS ukey, run, v, {rows} AS m FROM {source} s0, (SELECT count(*) AS users FROM {source} s1), (SELECT range AS run FROM range({runs})))))
    GROUP BY run, s), (SELECT range::INT AS code FROM range({k})) GROUP BY run, code)
JOIN (SELECT c.range::INT AS code, count(v) / any_value(users)::double AS exact FROM range({k}) c LEFT JOIN {source} s2 ON v = c.range, (SELECT count(*) AS users FROM {source} s3) GROUP BY 1) USING (code)"""

    return part("orthogonal") + " UNION ALL " + part("projection")


def dimension_errors(source: str, dims: list[int], eps: float, runs: int) -> str:
    """(method, d, rms) of three methods on the first d places of ``source``'s vector x, over several runs; half-space up to 16."""
    parts = []
    for n in dims:
        errors = lambda method, rows: f"SELECT '{method}' AS method, {n} AS d, round(sqrt(avg((estimate - exact) * (estimate - exact))), 9) AS rms FROM ({rows}) JOIN truth USING (i)"  # noqa: E731,B023
        place = lambda salt: u("ukey", f"{salt}:e' || i::varchar || '", run="run")
        one = one_coordinate("many", [f"x[{i + 1}]" for i in range(n)], eps, run="run", more="run,")
        sums = f"SELECT run, j AS i, {d(C.report_scale(eps) * n)} * sum(sign) / (SELECT count(*) FROM v) AS estimate FROM {one} r GROUP BY run, j"
        parts.append(errors("one_coordinate", sums))
        long = f"(SELECT run, ukey, x, unnest(range({n})) AS i FROM many)"
        noise = f"{d(2 * n / eps)} * sign({place('lap')} - 0.5) * ln(greatest(1 - 2 * abs({place('lap')} - 0.5), 2::double ** -53))"
        parts.append(errors("laplace", f"SELECT run, i, avg(x[i + 1] - {noise}) AS estimate FROM {long} GROUP BY run, i"))
        if n <= 16:
            at = lambda cdf: " + ".join(f"(case when {u('ukey', 'agree', run='run')} >= {d(x)} then 1 else 0 end)" for x in cdf[:-1]) or "0"
            inside, other = C.halfspace_cdf(n)
            agree = f"case when {u('ukey', 'side', run='run')} < {d(C.halfspace_prob(n, eps, 'repaired'))} then {at(inside)} else {at(other)} end"
            signs = f"SELECT run, i, {agree} AS a, case when {place('round')} < (x[i + 1] + 1) / 2 then 1 else -1 end AS sign, row_number() OVER (PARTITION BY run, ukey ORDER BY {place('subset')}) AS nth FROM {long}"
            parts.append(errors("half_space", f"SELECT run, i, {d(C.halfspace_scale(n, eps))} * sum(case when nth <= a then sign else -sign end) / count(*) AS estimate FROM ({signs}) GROUP BY run, i"))
    return f"""
WITH v AS MATERIALIZED (SELECT * FROM {source} s0), many AS (SELECT ukey, x, run FROM v, (SELECT range AS run FROM range({runs}))),
truth AS MATERIALIZED (SELECT i, avg(x[i + 1]) AS exact FROM (SELECT x, unnest(range({max(dims)})) AS i FROM v) GROUP BY i)
{' UNION ALL '.join(parts)}"""


def slope(kind: str, score: str, y: str) -> str:
    if kind == "linear":
        return f"(2 * ({score} - {y}))"
    if kind == "logistic":
        z = f"({y} * ({score}))"
        return f"(-{y} * (case when {z} >= 0 then exp(-abs{z}) / (1 + exp(-abs{z})) else 1 / (1 + exp(-abs{z})) end))"
    return f"(case when {y} * ({score}) < 1 then -{y} else 0 end)"


def descent(source: str, xs: list[str], kind: str, eps: float, steps: int, lam: float, gamma0: float = 1.0) -> str:
    """(j, weight) after ``steps`` mini-batches, each step a query of its own: ``source`` gives ukey, y and the columns behind ``xs``."""
    dim = len(xs)
    tilt, c = 1 / (2 * C.report_scale(eps)), C.report_scale(eps)
    xcols = ", ".join(f"({x})::double AS x{i}" for i, x in enumerate(xs))
    parts = [
        f"v AS MATERIALIZED (SELECT ukey, y, {xcols}, {u('ukey', 'batch')} AS ub, {u('ukey', 'step')} AS uj, {u('ukey', 'grad')} AS ut FROM {source} s0)",
        f"b AS MATERIALIZED (SELECT *, least(floor(ub * {steps})::INT, {steps - 1}) AS batch, floor(uj * {dim})::INT AS j FROM v)",
        "a0 AS (SELECT " + ", ".join(f"0.0::double AS w{i}" for i in range(dim)) + ")",
    ]
    score = "(0.0::double" + "".join(f" + x{i} * w{i}" for i in range(dim)) + ")"
    for t in range(steps):
        xj, wj = pick("j", [f"x{i}" for i in range(dim)]), pick("j", [f"w{i}" for i in range(dim)])
        g = f"{slope(kind, score, 'y')} * {xj} + {d(lam)} * {wj}"
        sums = ", ".join(f"coalesce(sum(sign) FILTER (WHERE j = {i}), 0)::BIGINT AS t{i}" for i in range(dim))
        parts.append(f"s{t} AS MATERIALIZED (SELECT count(*) AS n, {sums} FROM (SELECT j, case when ut < 0.5::double + greatest(-1.0::double, least(1.0::double, {g})) * {d(tilt)} then 1 else -1 end AS sign FROM b, a{t} WHERE batch = {t}) q)")
        rate = d(gamma0 / (t + 1) ** 0.5 * c * dim)
        parts.append(f"a{t + 1} AS MATERIALIZED (SELECT " + ", ".join(f"w{i} - {rate} / n * t{i} AS w{i}" for i in range(dim)) + f" FROM a{t}, s{t})")
    final = " UNION ALL ".join(f"SELECT {i} AS j, round(w{i}, 9) AS weight FROM a{steps}" for i in range(dim))
    return f"WITH {', '.join(parts)} {final}"


def sequential(source: str, xs: list[str], kind: str, users: int, lam: float, gamma0: float) -> str:
    """(j, weight) of exact descent over the first users by a recursive query."""
    dim = len(xs)
    xcols = ", ".join(f"({x})::double AS x{i}" for i, x in enumerate(xs))
    score = "(0.0::double" + "".join(f" + x{i} * w{i}" for i in range(dim)) + ")"
    moved = ", ".join(f"w{i} - {d(gamma0)} / sqrt(o.nth::double) * ({slope(kind, score, 'y')} * x{i} + {d(lam)} * w{i})" for i in range(dim))
    zeros = ", ".join(f"0.0::double AS w{i}" for i in range(dim))
    final = " UNION ALL ".join(f"SELECT {i} AS j, round(w{i}, 9) AS weight FROM r WHERE nth = {users}" for i in range(dim))
    return f"""
WITH RECURSIVE o AS MATERIALIZED (SELECT * FROM (SELECT ukey, y, {xcols}, row_number() OVER (ORDER BY {u('ukey', 'batch')}, ukey) AS nth FROM {source} s0) z WHERE nth <= {users}),
r AS (SELECT 0::BIGINT AS nth, {zeros} UNION ALL SELECT o.nth, {moved} FROM r JOIN o ON o.nth = r.nth + 1)
{final}"""
