"""Pieces of DuckDB SQL: standardised rows, cluster sets (CTE k: id, n, m1, m2, a, b, c), pairs (CTE y) and measures over y."""

Z = (
    "st AS (SELECT avg(l_quantity) AS a1, stddev_samp(l_quantity) AS s1, avg(l_extendedprice) AS a2, stddev_samp(l_extendedprice) AS s2, avg(l_discount) AS a3, stddev_samp(l_discount) AS s3, avg(l_tax) AS a4, stddev_samp(l_tax) AS s4 FROM lineitem), "
    "z AS (SELECT l.*, (l_quantity-a1)/s1 AS z1, (l_extendedprice-a2)/s2 AS z2, (l_discount-a3)/s3 AS z3, (l_tax-a4)/s4 AS z4 FROM lineitem l, st)"
)
_AGG = "count(*) AS n, avg(z1) AS m1, avg(z2) AS m2, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c"
FLAGS = f"k AS (SELECT CAST(ascii(l_returnflag)*1000+ascii(l_linestatus) AS BIGINT) AS id, {_AGG} FROM z GROUP BY 1)"
SUPPLIERS = f"k AS (SELECT CAST(l_suppkey AS BIGINT) AS id, {_AGG} FROM z GROUP BY 1)"
BRANDS = "k AS (SELECT CAST(regexp_extract(p_brand, '([0-9]+)$', 1) AS BIGINT) AS id, count(*) AS n, avg(CAST(p_size AS DOUBLE)) AS m1, avg(p_retailprice) AS m2, var_samp(CAST(p_size AS DOUBLE)) AS a, covar_samp(CAST(p_size AS DOUBLE), p_retailprice) AS b, var_samp(p_retailprice) AS c FROM part GROUP BY 1)"
DISCS = (
    "dk AS (SELECT i AS disc, ((37*i) % 24)/23.0::DOUBLE*2.8::DOUBLE-1.4::DOUBLE AS x, ((17*i+5) % 24)/23.0::DOUBLE*2.8::DOUBLE-1.4::DOUBLE AS y, 0.35::DOUBLE+0.05::DOUBLE*(i % 5) AS r FROM range(24) t(i)), "
    f"k AS (SELECT CAST(disc AS BIGINT) AS id, {_AGG} FROM z JOIN dk ON (z1-x)*(z1-x)+(z2-y)*(z2-y) <= r*r GROUP BY 1)"
)
_TIGHT = "l_quantity BETWEEN 23 AND 28 AND l_extendedprice BETWEEN 47000 AND 59000"
_LOOSE = "l_quantity BETWEEN 21 AND 30 AND l_extendedprice BETWEEN 40000 AND 66000"
_U, _V = "(z1+z2)/sqrt(2.0)", "(z1-z2)/sqrt(2.0)"
_SQUARE = f"abs({_U}) < 1.5 AND abs({_V}) < 1.5"
SIDES = [
    ("a", 0, "l_returnflag = 'A' AND l_linestatus = 'F'"),
    ("a", 1, "l_returnflag = 'R' AND l_linestatus = 'F'"),
    ("b", 0, "l_quantity <= 10 AND l_extendedprice <= 25000"),
    ("b", 1, "l_quantity >= 41 AND l_extendedprice >= 80000"),
    ("c_tight", 0, f"NOT ({_TIGHT})"),
    ("c_tight", 1, _TIGHT),
    ("c_loose", 0, f"NOT ({_LOOSE})"),
    ("c_loose", 1, _LOOSE),
    ("d_axis", 0, "l_quantity BETWEEN 24 AND 27 AND NOT (l_extendedprice BETWEEN 49000 AND 57000)"),
    ("d_axis", 1, "l_extendedprice BETWEEN 49000 AND 57000 AND NOT (l_quantity BETWEEN 24 AND 27)"),
    ("d_diag", 0, f"{_SQUARE} AND abs({_U}) < 0.2 AND NOT (abs({_V}) < 0.2)"),
    ("d_diag", 1, f"{_SQUARE} AND abs({_V}) < 0.2 AND NOT (abs({_U}) < 0.2)"),
]
SCENARIO_K = "sk AS (" + " UNION ALL ".join(f"SELECT '{s}' AS scenario, CAST({k} AS BIGINT) AS id, {_AGG} FROM z WHERE {on}" for s, k, on in SIDES) + ")"
_PR = "SELECT p.id AS left_id, q.id AS right_id, p.n AS n1, q.n AS n2, p.m1-q.m1 AS d1, p.m2-q.m2 AS d2, p.a AS a1, p.b AS b1, p.c AS c1, q.a AS a2, q.b AS b2, q.c AS c2 FROM {k} p JOIN {k} q ON p.id < q.id"
_X = "SELECT *, (a1+a2)/2 AS aa, (b1+b2)/2 AS ba, (c1+c2)/2 AS ca, ((n1-1)*a1+(n2-1)*a2)/(n1+n2-1) AS aw, ((n1-1)*b1+(n2-1)*b2)/(n1+n2-1) AS bw, ((n1-1)*c1+(n2-1)*c2)/(n1+n2-1) AS cw, n1*n2/((n1+n2)*(n1+n2-1)) AS g FROM {of}"
_Y = "SELECT *, aa*ca-ba*ba AS da, aw*cw-bw*bw AS dw, (aw+g*d1*d1)*(cw+g*d2*d2)-(bw+g*d1*d2)*(bw+g*d1*d2) AS df, a1*c1-b1*b1 AS e1, a2*c2-b2*b2 AS e2, (ca*d1*d1-2*ba*d1*d2+aa*d2*d2)/(aa*ca-ba*ba) AS mh FROM {of}"
PAIRS = f"pr AS ({_PR.format(k='k')}), x AS ({_X.format(of='pr')}), y AS ({_Y.format(of='x')})"
MEASURE_SQL = {
    "b": "mh/8+0.5*ln(da/sqrt(e1*e2))",
    "kl1": "0.5*((ca*a1-2*ba*b1+aa*c1)/da+ln(da/e1)+mh/4-2)",
    "kl2": "0.5*((ca*a2-2*ba*b2+aa*c2)/da+ln(da/e2)+mh/4-2)",
    "w": "d1*d1+d2*d2+a1+c1+a2+c2-2*sqrt(a1*a2+2*b1*b2+c1*c2+2*sqrt(e1*e2))",
    "vr": "df/(e1+e2)",
    "ab": "mh/8+0.5*ln(da/((e1+e2)/2))",
    "o": "ln(df/((e1+e2)/2))",
    "oh": "ln((aw+g*d1*d1)*(cw+g*d2*d2)/((a1*c1+a2*c2)/2))",
}
MEASURE_SQL["js"] = f"(({MEASURE_SQL['kl1']})+({MEASURE_SQL['kl2']}))/2"


def fused_rows(_: str) -> str:
    """CTE f: every pair of flag clusters, summarised from the union of their raw rows."""
    ids = "ids AS (SELECT DISTINCT ascii(l_returnflag)*1000+ascii(l_linestatus) AS id FROM lineitem)"
    return f"{ids}, f AS (SELECT CAST(p.id AS BIGINT) AS left_id, CAST(q.id AS BIGINT) AS right_id, CAST(count(*) AS BIGINT) AS n, avg(z1) AS m1, var_samp(z1) AS a, covar_samp(z1,z2) AS b, var_samp(z2) AS c FROM ids p JOIN ids q ON p.id < q.id JOIN z ON ascii(l_returnflag)*1000+ascii(l_linestatus) IN (p.id, q.id) GROUP BY 1, 2)"


def _product(a: str, b: str, dim: int) -> str:
    """Product of two matrices that are lists of rows."""
    axes = f"range(1, {dim + 1})"
    return f"list_transform({a}, lambda r: list_transform({axes}, lambda j: list_sum(list_transform({axes}, lambda k: r[k] * {b}[k][j]))))"


def matrix_pairs(rows: str, dim: int) -> str:
    """CTEs (after WITH RECURSIVE) from ``rows``, which define e: id, rid, i, x. They end in y: all but w for every pair of ids.

    Matrices are lists of rows. Determinants are the pivots of an elimination; a border of d leaves the Mahalanobis term."""
    matrix = "list_transform(s, lambda r, i: list_transform(r, lambda v, j: {}))"
    bordered = "list_append(list_transform({0}, lambda r, i: list_append(r, d[i])), list_append(d, 0.0::DOUBLE))"
    avg = matrix.format("(v + t[i][j]) / 2")
    fused = matrix.format("((n1-1)*v + (n2-1)*t[i][j]) / (n1+n2-1) + n1/(n1+n2)*n2/(n1+n2-1)*d[i]*d[j]")
    whole = {"p": "s", "q": "t", "avg": "ma", "fused": "mf"}
    start = " UNION ALL ".join(f"SELECT left_id, right_id, '{w}' AS which, 0 AS step, 0.0::DOUBLE AS l, {bordered.format(c)} AS m FROM pm" for w, c in whole.items())
    diagonal = lambda c: f"list_sum(list_transform({c}, lambda r, i: ln(r[i])))"
    return (
        f"{rows}, ce AS (SELECT a.id, a.i, b.i AS j, covar_samp(a.x, b.x) AS v FROM e a JOIN e b ON a.id = b.id AND a.rid = b.rid GROUP BY 1, 2, 3), "
        "km AS (SELECT id, list(r ORDER BY i) AS s FROM (SELECT id, i, list(v ORDER BY j) AS r FROM ce GROUP BY 1, 2) GROUP BY 1), "
        "mu AS (SELECT id, max(n)::DOUBLE AS n, list(m ORDER BY i) AS m FROM (SELECT id, i, count(*) AS n, avg(x) AS m FROM e GROUP BY 1, 2) GROUP BY 1), "
        "k AS (SELECT id, n, m, s FROM mu JOIN km USING (id)), "
        "pb AS (SELECT p.id AS left_id, q.id AS right_id, p.n AS n1, q.n AS n2, p.s AS s, q.s AS t, list_transform(p.m, lambda v, i: v - q.m[i]) AS d FROM k p JOIN k q ON p.id < q.id), "
        f"pm AS (SELECT *, {avg} AS ma, {fused} AS mf FROM pb), "
        f"el AS ({start} UNION ALL SELECT left_id, right_id, which, step + 1, l + ln(m[1][1]), list_transform(m[2:], lambda r: list_transform(r[2:], lambda v, j: v - r[1] * m[1][j + 1] / m[1][1])) FROM el WHERE step < {dim}), "
        f"de AS (SELECT left_id, right_id, max(l) FILTER (which = 'p') AS lp, max(l) FILTER (which = 'q') AS lq, max(l) FILTER (which = 'avg') AS la, max(l) FILTER (which = 'fused') AS lf, max(-m[1][1]) FILTER (which = 'avg') AS mh FROM el WHERE step = {dim} GROUP BY 1, 2), "
        # the two sides of js share the average, so their traces add up to the dimension
        "y AS (SELECT *, mh/8+0.5*(la-0.5*(lp+lq)) AS b, mh/8+0.5*(la-0.5*(lp+lq)) AS js, exp(lf)/(exp(lp)+exp(lq)) AS vr, mh/8+0.5*(la-ln((exp(lp)+exp(lq))/2)) AS ab, lf-ln((exp(lp)+exp(lq))/2) AS o, "
        f"{diagonal('mf')}-ln((exp({diagonal('s')})+exp({diagonal('t')}))/2) AS oh FROM de JOIN pm USING (left_id, right_id))"
    )


def all_measures(rows: str, dim: int, steps: int = 45) -> str:
    """Rows left_id, right_id, n1, n2 and the seven measures; the root of the product of two covariances is iterated."""
    axes = f"range(1, {dim + 1})"
    unit = f"list_transform({axes}, lambda i: list_transform({axes}, lambda j: CASE WHEN i = j THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END))"
    trace = lambda c: f"list_sum(list_transform({c}, lambda r, i: r[i]))"
    return (
        f"WITH RECURSIVE {matrix_pairs(rows, dim)}, "
        f"st0 AS (SELECT left_id, right_id, {_product('s', 't', dim)} AS st FROM pm), "
        f"sc AS (SELECT left_id, right_id, {trace('st')} AS c, st FROM st0), "
        f"ro AS (SELECT left_id, right_id, c, 0 AS step, list_transform(st, lambda r: list_transform(r, lambda v: v / c)) AS u, {unit} AS z FROM sc "
        f"UNION ALL SELECT left_id, right_id, c, step + 1, {_product('u', 'h', dim)}, {_product('h', 'z', dim)} FROM "
        f"(SELECT *, list_transform(zu, lambda r, i: list_transform(r, lambda v, j: (CASE WHEN i = j THEN 3 ELSE 0 END - v) / 2)) AS h FROM (SELECT *, {_product('z', 'u', dim)} AS zu FROM ro WHERE step < {steps}))), "
        f"rt AS (SELECT left_id, right_id, sqrt(c) * {trace('u')} AS root FROM ro WHERE step = {steps}) "
        "SELECT CAST(left_id AS BIGINT) AS left_id, CAST(right_id AS BIGINT) AS right_id, CAST(n1 AS BIGINT) AS n1, CAST(n2 AS BIGINT) AS n2, round(b,6)+0.0 AS b, round(js,6)+0.0 AS js, "
        f"round(list_sum(list_transform(d, lambda v: v*v))+{trace('s')}+{trace('t')}-2*root,6)+0.0 AS w, round(vr,6)+0.0 AS vr, round(ab,6)+0.0 AS ab, round(o,6)+0.0 AS o, round(oh,6)+0.0 AS oh FROM y JOIN rt USING (left_id, right_id)"
    )


def pairs_of(k: str) -> str:
    """What CTE y is for k, as one subquery over another table of clusters."""
    return f"({_Y.format(of=f'({_X.format(of=f"({_PR.format(k=k)})")})')})"


def iterated(chosen: str) -> str:
    """CTEs (after WITH RECURSIVE and k): step(round, id, n, m1, m2, a, b, c, members), where each round fuses the pairs (l, r) of ``chosen``, a query of step."""
    moments = ", ".join(f"(sum((n-1)*{v} + n*{i}*{j}) - sum(n)*(sum(n*{i})/sum(n))*(sum(n*{j})/sum(n)))/(sum(n)-1) AS {v}" for v, i, j in (("a", "m1", "m1"), ("b", "m1", "m2"), ("c", "m2", "m2")))
    # n becomes a double, as sums of whole numbers have another type than their parts
    start = "SELECT 0 AS round, id, n::DOUBLE AS n, m1, m2, a, b, c, [id] AS members FROM k"
    # a round without a pair has no rows, which ends it
    fused = f"SELECT round + 1 AS round, to_id AS id, sum(n)::DOUBLE AS n, sum(n*m1)/sum(n) AS m1, sum(n*m2)/sum(n) AS m2, {moments}, list_sort(flatten(list(members))) AS members"
    moved = f"SELECT s.*, coalesce(h.l, s.id) AS to_id FROM step s JOIN (SELECT count(*) AS made FROM ({chosen})) ON made > 0 LEFT JOIN ({chosen}) h ON s.id = h.r"
    return f"step AS ({start} UNION ALL {fused} FROM ({moved}) GROUP BY round, to_id)"


_WEIGHED = f"SELECT left_id, right_id, {MEASURE_SQL['o']} AS o FROM {pairs_of('step')}"
BEST_PAIR = f"SELECT left_id AS l, right_id AS r FROM ({_WEIGHED}) WHERE o < 1.5 ORDER BY o, l, r LIMIT 1"
_BOTH = f"SELECT left_id AS x, right_id AS y, left_id AS l, right_id AS r, o FROM ({_WEIGHED}) WHERE o < 1.5 UNION ALL SELECT right_id, left_id, left_id, right_id, o FROM ({_WEIGHED}) WHERE o < 1.5"
#: A pair is best for both of its sides if it is chosen twice.
MUTUAL_PAIRS = f"SELECT l, r FROM (SELECT l, r, row_number() OVER (PARTITION BY x ORDER BY o, l, r) AS place FROM ({_BOTH})) WHERE place = 1 GROUP BY l, r HAVING count(*) = 2"


def psi(x: str) -> str:
    """Digamma by its expansion beyond 8 and the recurrence below."""
    return f"(ln({x}+8)-0.5/({x}+8)-1/(12*({x}+8)^2)+1/(120*({x}+8)^4)-1/(252*({x}+8)^6)+1/(240*({x}+8)^8)-list_sum(list_transform(range(8), lambda k: 1/({x}+k))))"


def psi1(x: str) -> str:
    """Trigamma in the same way."""
    return f"(1/({x}+8)+0.5/({x}+8)^2+1/(6*({x}+8)^3)-1/(30*({x}+8)^5)+1/(42*({x}+8)^7)+list_sum(list_transform(range(8), lambda k: 1/(({x}+k)^2))))"
