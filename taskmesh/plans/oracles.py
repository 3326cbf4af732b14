"""DuckDB SQL for the queries that SQL can express, on views of the same tables."""

from __future__ import annotations

from taskmesh.functions.draws import uniform_sql
from taskmesh.operators.frames import poisson_steps
from taskmesh.plans.workloads import EVENT_TYPES, LANGUAGES, LETTERS, SEGMENTS

M, D = 20, 64
LAM1, LAM2 = 1.0, 0.5

NATION_ROWS = "SELECT c_nationkey::BIGINT AS task_id, o_orderkey AS row_id, CASE WHEN o_orderstatus = 'F' THEN 1.0 ELSE -1.0 END AS label FROM orders JOIN customer ON o_custkey = c_custkey"
SENSOR = f"""SELECT vec_id % {M} AS task_id, vec_id AS row_id, embedding::DOUBLE[] AS x,
  CASE WHEN label < 5 THEN 1.0 ELSE -1.0 END AS y FROM embeddings"""
CLUSTERS = f"SELECT range AS task_id, (range % 3)::INTEGER AS cluster_id FROM range({M})"
#: A task's points times labels, summed, one row per coordinate.
SHARED = f"SELECT task_id, c.range::INTEGER AS coordinate, sum(x[c.range + 1] * y) AS v FROM ({SENSOR}), range({D}) c GROUP BY 1, 2"
WEIGHTS = f"""SELECT task_id, cluster_id, coordinate, 0.5 * ((v - mean) / {LAM1 + LAM2} + mean / {LAM2}) AS w FROM
  (SELECT s.*, cluster_id, avg(v) OVER (PARTITION BY cluster_id, coordinate) AS mean FROM ({SHARED}) s JOIN ({CLUSTERS}) USING (task_id))"""
SCORED = f"SELECT p.task_id, row_id, y, sum(x[w.coordinate + 1] * w) AS z FROM ({SENSOR}) p JOIN ({WEIGHTS}) w ON p.task_id = w.task_id GROUP BY ALL"
SPLIT = f"""SELECT *, CASE WHEN row_number() OVER (PARTITION BY task_id ORDER BY u, row_id) <= ceil(count(*) OVER (PARTITION BY task_id) * 0.75) THEN 'train' ELSE 'test' END AS split
  FROM (SELECT *, {uniform_sql("'split'", "'0'", "'0'", "task_id::VARCHAR", "row_id::VARCHAR")} AS u FROM ROWS)"""
LOG = f"""SELECT 'x' AS run, 0 AS "outer", round, task_id, CASE WHEN dropped THEN 0 ELSE steps END AS steps, dropped, CASE WHEN dropped THEN 1.0 ELSE 1.0 / steps END AS theta,
  CASE WHEN dropped THEN 0 ELSE steps END * 40.0 AS flops, CASE WHEN dropped THEN 0 ELSE 20 END AS comm_elems FROM
  (SELECT s_suppkey AS task_id, range::INTEGER AS round, floor(10 + 90 * {uniform_sql("'steps'", "s_suppkey::VARCHAR", "range::VARCHAR")})::INTEGER AS steps,
    {uniform_sql("'gone'", "s_suppkey::VARCHAR", "range::VARCHAR")} < 0.1 AS dropped FROM supplier, range(8))"""
FEATURES_SUM = "list_sum(x)"


def _local(step: str, budget: int = 1 << 30) -> str:
    """One cyclic pass by recursion. step: the new dual from a (dual), y, xu and q."""
    u = ", ".join(f"u[{j}] + 1.5 * ({{new}} - a[i]) * xs[i][{j}]" for j in range(1, D + 1))
    new = f"CASE WHEN k < {budget} THEN {step.format(a='a[i]', y='ys[i]', xu='xu', q='(1.5 * norms[i])')} ELSE a[i] END"
    dot = " + ".join(f"xs[i][{j}] * u[{j}]" for j in range(1, D + 1))
    return f"""WITH RECURSIVE packed AS (SELECT task_id, list(x ORDER BY row_id) AS xs, list(y ORDER BY row_id) AS ys, list(list_dot_product(x, x) ORDER BY row_id) AS norms, count(*) AS n
      FROM ({SENSOR}) GROUP BY task_id),
    run AS (SELECT task_id, xs, ys, norms, n, 1::BIGINT AS i, [{", ".join(["0.0::DOUBLE"] * D)}] AS u, list_transform(ys, lambda y: 0.0::DOUBLE) AS a, 0::INTEGER AS k FROM packed
      UNION ALL SELECT task_id, xs, ys, norms, n, i + 1, [{u.format(new="new")}], a, k + CASE WHEN k < {budget} THEN 1 ELSE 0 END FROM
        (SELECT *, {new} AS new FROM (SELECT *, {dot} AS xu FROM run WHERE i <= n)))
    SELECT task_id, k AS steps, c.range::INTEGER AS coordinate, round(u[c.range + 1], 6) AS u FROM run, range({D}) c WHERE i = n + 1"""


HINGE = "{y} * greatest(0.0, least(1.0, {y} * {a} + (1.0 - {y} * {xu}) / {q}))"
SQUARED = "{a} + ({y} - {xu} - {a}) / ({q} + 1.0)"
SMOOTH = "{y} * greatest(0.0, least(1.0, {y} * {a} + (1.0 - {y} * {xu} - {y} * {a} * 0.5) / ({q} + 0.5)))"
ABSOLUTE = "greatest(-1.0, least(1.0, {a} + ({y} - {xu}) / {q}))"


def _first_round(gamma: float) -> str:
    """Each task's pass from zero, brought back as vectors, then mixed; kappa and sigma as the cluster relation has them."""
    local = _local(HINGE)
    for old in ("1.5 *",):
        local = local.replace(old, "curve *")
    kappa = f"0.5 * ((1 - 1.0 / c) / {LAM1 + LAM2} + 1.0 / (c * {LAM2}))"
    sized = f"(SELECT task_id, cluster_id, count(*) OVER (PARTITION BY cluster_id) AS c FROM ({CLUSTERS}))"
    local = local.replace("count(*) AS n\n", f"count(*) AS n, any_value(3.0 * {kappa}) AS curve\n").replace(f"FROM ({SENSOR}) GROUP BY task_id", f"FROM ({SENSOR}) JOIN {sized} USING (task_id) GROUP BY task_id")
    local = local.replace("norms, n,", "norms, n, curve,").replace("round(u[c.range + 1], 6) AS u", "u[c.range + 1] / curve AS v")
    return f"""SELECT task_id, coordinate, round({gamma} * 0.5 * ((v - mean) / {LAM1 + LAM2} + mean / {LAM2}), 6) AS x FROM
      (SELECT l.*, avg(v) OVER (PARTITION BY cluster_id, coordinate) AS mean FROM ({local}) l JOIN ({CLUSTERS}) USING (task_id))"""


def _loss(expression: str) -> str:
    return f"SELECT task_id, round(sum({expression}), 5) AS loss FROM ({SCORED}) GROUP BY task_id"


def _time(rho: float) -> str:
    return f"""SELECT round, seconds, comm_elems, flops, sum(seconds) OVER (ORDER BY round) AS sim_time FROM
      (SELECT round, max(flops + {rho} * comm_elems) AS seconds, sum(comm_elems)::BIGINT AS comm_elems, sum(flops) AS flops FROM ({LOG}) GROUP BY round)"""


def _mix(clusters: str | None, shared: str = SHARED) -> str:
    if clusters is None:
        return f"SELECT task_id, coordinate, round(v / {2 * LAM2}, 6) AS x FROM ({shared})"
    return f"""SELECT task_id, coordinate, round(0.5 * ((v - mean) / {LAM1 + LAM2} + mean / {LAM2}), 6) AS x FROM
      (SELECT s.*, avg(v) OVER (PARTITION BY cluster_id, coordinate) AS mean FROM ({shared}) s JOIN ({clusters}) USING (task_id))"""


MONTH = "(2 * pi() / 12)"
ORDER_FEATURES = (
    "[ln(1 + o_totalprice) / 10.0, " + ", ".join(f"CASE WHEN o_orderpriority[1] = '{p}' THEN 1.0 ELSE 0.0 END" for p in range(1, 6))
    + f", sin(month(o_orderdate) * {MONTH}), cos(month(o_orderdate) * {MONTH}), (dayofweek(o_orderdate) + 1) / 7.0, c_acctbal / 10000.0, "
    + ", ".join(f"CASE WHEN c_mktsegment = '{s}' THEN 1.0 ELSE 0.0 END" for s in SEGMENTS) + ", 1.0]"
)
REGION_SHARED = f"""SELECT task_id, c.range::INTEGER AS coordinate, sum(x[c.range + 1] * y) AS v FROM
  (SELECT c_nationkey::BIGINT AS task_id, {ORDER_FEATURES} AS x, CASE WHEN o_orderstatus = 'F' THEN 1.0 ELSE -1.0 END AS y FROM orders JOIN customer ON o_custkey = c_custkey), range(16) c GROUP BY 1, 2"""
REGIONS = "SELECT n_nationkey::BIGINT AS task_id, n_regionkey AS cluster_id FROM nation"
SUPPLIER_X = f"""[l_quantity / 50.0, ln(1 + l_extendedprice) / 10.0, l_discount * 10.0, l_tax * 10.0, p_size / 50.0, p_retailprice / 2000.0, sin(month(l_shipdate) * {MONTH}), cos(month(l_shipdate) * {MONTH}),
  CASE WHEN l_linestatus = 'O' THEN 1.0 ELSE 0.0 END, 1.0]"""
CONVERSATION_X = """[ln(1 + length(t)) / 10.0, length(regexp_replace(t, '[^?]', '', 'g')) / n, length(regexp_replace(t, '[^0-9]', '', 'g')) / n, length(regexp_replace(t, '[^ ]', '', 'g')) / n, 1.0]"""


def _summary(rows: str, d: int) -> str:
    return f"SELECT task_id, count(*) AS n, count(*) FILTER (label > 0) AS positives, round(avg(list_sum(x)), 4) AS mean_feature_sum, {d} AS d FROM ({rows}) GROUP BY task_id"


def _planted(rows: str, group: str, d: int) -> str:
    """Labels of planted hyperplanes: rows have task_id, row_id, x; group: of a task."""
    base, own = (uniform_sql(f"'{kind}'", "'0'", f"({who})::VARCHAR", "j.range::VARCHAR") for kind, who in (("base", group), ("own", "task_id")))
    flip = uniform_sql("'flip'", "'0'", "r.task_id::VARCHAR", "r.row_id::VARCHAR")
    return f"""WITH r AS ({rows}), u AS (SELECT task_id, list(2 * {base} - 1 + 0.3 * (2 * {own} - 1) ORDER BY j.range) AS u FROM (SELECT DISTINCT task_id FROM r), range({d}) j GROUP BY task_id)
      SELECT r.task_id, r.row_id, r.x, CASE WHEN (list_dot_product(r.x, u.u) >= 0) <> ({flip} < 0.03) THEN 1.0 ELSE -1.0 END AS label FROM r JOIN u ON r.task_id = u.task_id"""


SENSOR_PLANTED = _planted("SELECT vec_id % 23 AS task_id, vec_id AS row_id, list_append(embedding::DOUBLE[], 1.0::DOUBLE) AS x FROM embeddings", "task_id % 3", 65)
ORDER_ROWS = f"SELECT {{task}} AS task_id, o_orderkey AS row_id, {ORDER_FEATURES}::DOUBLE[] AS x, CASE WHEN o_orderstatus = 'F' THEN 1.0 ELSE -1.0 END AS label FROM orders JOIN customer ON o_custkey = c_custkey"
NATION_PLANTED = _planted(ORDER_ROWS.format(task="c_nationkey::BIGINT"), "(SELECT n_regionkey FROM nation WHERE n_nationkey = task_id)", 16)


def _letters(low: str) -> str:
    """The list of letters' shares; low: lower-cased text."""
    return "[" + ", ".join(f"(length({low}) - length(replace({low}, '{c}', ''))) / greatest(length(regexp_replace({low}, '[^a-z]', '', 'g')), 1)" for c in LETTERS) + "]"


#: Shares of letter pairs sum to one wherever there is a pair.
LANGUAGE_ROWS = f"""SELECT task_id, list_sum({_letters('low')}) + CASE WHEN length(low) >= 2 THEN 1 ELSE 0 END + ln(1 + n_chars) / 10.0 + 1.0 AS s,
  CASE WHEN lang = [{', '.join(f"'{c}'" for c in LANGUAGES)}][(task_id % 4 + 1)::INT] THEN 1.0 ELSE -1.0 END AS label
  FROM (SELECT *, lower(text) AS low, regexp_extract(source, '([0-9]+)$', 1)::BIGINT AS task_id FROM documents WHERE text IS NOT NULL)"""
QUALITY_ROWS = """SELECT CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END::BIGINT AS task_id, CASE WHEN quality = 1 THEN 1.0 ELSE -1.0 END AS label,
  length(regexp_replace(text, '[\\p{L}\\s]', '', 'g')) / n + length(regexp_replace(text, '[^0-9]', '', 'g')) / n + 1.0 - len(list_distinct(string_split(text, chr(10)))) / len(string_split(text, chr(10)))
    + length(regexp_replace(text, '\\s', '', 'g')) / len(string_split_regex(text, '\\s+')) / 10.0 + ln(1 + length(text)) / 10.0 + 1.0 AS s
  FROM (SELECT *, greatest(length(text), 1) AS n FROM documents JOIN labels USING (doc_id) WHERE text IS NOT NULL)"""
HOST_ROWS = f"""SELECT ('0x' || substr(md5(regexp_extract(url, '^[a-z]+://([^/:]+)', 1)), 1, 8))::BIGINT AS task_id, CASE WHEN regexp_extract(html, 'lang="([a-z]+)', 1) = 'en' THEN 1.0 ELSE -1.0 END AS label,
  list_sum({_letters('low')}) + ln(1 + length(html)) / 10.0 + length(regexp_replace(html, '[^<]', '', 'g')) / greatest(length(html), 1) + 1.0 AS s
  FROM (SELECT *, lower(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS low FROM pages WHERE html IS NOT NULL)"""


def _wave(f: int) -> str:
    parts = ["(" + " + ".join(f"e{e} * {trig}(2 * pi() * {f} * {e} / 8)" for e in range(8)) + ")" for trig in ("cos", "sin")]
    return f"sqrt(pow({parts[0]}, 2) + pow({parts[1]}, 2)) / 1000.0"


EVENT_ROWS = f"""SELECT user_id AS task_id, CASE WHEN is_purchase > 0 THEN 1.0 ELSE -1.0 END AS label,
    n / 10.0 + (mean + sd + least + most + q1 + q2 + q3) / 100.0 + energy / 1e4 + lag1 + gap / 86400.0 + k / 100.0 + s1 + c1 + {' + '.join(f'is_{t}' for t in EVENT_TYPES[:-1])} + {' + '.join(_wave(f) for f in range(5))}
    + (most_gap + least_gap) / 86400.0 + (most_k + least_k) / 100.0 + third / 1e6 + change / 100.0 + eighths / 8.0 + (most - least) / 100.0 + ({' + '.join(f'e{e}' for e in range(8))}) / 1000.0 + 1.0 AS s
  FROM (SELECT user_id, start, count(*) AS n, avg(value) AS mean, coalesce(stddev_pop(value), 0) AS sd, min(value) AS least, max(value) AS most, quantile_cont(value, 0.25) AS q1, quantile_cont(value, 0.5) AS q2,
    quantile_cont(value, 0.75) AS q3, avg(value * value) AS energy, coalesce(covar_pop(value, before) / nullif(stddev_pop(value) * stddev_pop(before), 0), 0) AS lag1, coalesce(avg(gap), 0) AS gap, coalesce(max(gap), 0) AS most_gap,
    coalesce(min(gap), 0) AS least_gap, coalesce(avg(k), 0) AS k, coalesce(max(k), 0) AS most_k, coalesce(min(k), 0) AS least_k, avg(pow(value, 3)) AS third, coalesce(avg(abs(value - before)), 0) AS change,
    count(DISTINCT eighth) AS eighths, avg(sin(hour(ts) * (2 * pi() / 24))) AS s1, avg(cos(hour(ts) * (2 * pi() / 24))) AS c1,
    {', '.join(f"avg((event_type = '{t}')::INT) AS is_{t}" for t in EVENT_TYPES)}, {', '.join(f"sum(CASE WHEN eighth = {e} THEN value ELSE 0 END) AS e{e}" for e in range(8))}
    FROM (SELECT e.*, epoch(date_trunc('day', ts))::BIGINT - 86400 * d.range AS start FROM (SELECT *, (epoch_us(ts) - lag(epoch_us(ts)) OVER w) / 1e6 AS gap, lag(value) OVER w AS before, hour(ts) // 3 AS eighth, (props::JSON->>'k')::INTEGER AS k, 1 AS one
      FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) e, range(2) d) GROUP BY user_id, start)"""


def _sums(rows: str, d: int) -> str:
    return f"SELECT task_id, count(*) AS n, count(*) FILTER (label > 0) AS positives, round(avg(s), 4) AS mean_feature_sum, {d} AS d FROM ({rows}) GROUP BY task_id"


KAPPA = f"0.5 * ((1 - 1.0 / c) / {LAM1 + LAM2} + 1.0 / (c * {LAM2}))"
#: The relations of the solver's queries: the cluster of each task, kappa, and weights from shared vectors and their means.
CLUSTERED = (f"SELECT task_id, cluster_id, {KAPPA} AS kappa FROM (SELECT *, count(*) OVER (PARTITION BY cluster_id) AS c FROM ({CLUSTERS}))", f"0.5 * ((v - mean) / {LAM1 + LAM2} + mean / {LAM2})")
ALONE = (f"SELECT range AS task_id, range AS cluster_id, {0.5 / LAM2} AS kappa FROM range({M})", f"v / {2 * LAM2}")


def _rounds(rounds: int, step: str, relation: tuple[str, str], sigma: float, gone: str = "false", mean_from: int | None = None) -> str:
    """Rounds of one cyclic pass by recursion, each from the duals and weights of the one before. gone: whether a task drops out
    of round {h}. mean_from: the weights of the mean of the states after this round and later ones."""
    clusters, mixed = relation
    dot = " + ".join(f"xs[i][{j}] * u[{j}]" for j in range(1, D + 1))
    moved = ", ".join(f"u[{j}] + curve * (new - a[i]) * xs[i][{j}]" for j in range(1, D + 1))
    new = step.format(a="a[i]", y="ys[i]", xu="xu", q="(curve * norms[i])")
    parts = [f"""packed AS (SELECT p.task_id, any_value(cluster_id) AS cluster_id, any_value(kappa) * {sigma} AS curve, list(x ORDER BY row_id) AS xs, list(y ORDER BY row_id) AS ys,
      list(list_dot_product(x, x) ORDER BY row_id) AS norms, count(*) AS n FROM ({SENSOR}) p JOIN ({clusters}) c ON p.task_id = c.task_id GROUP BY p.task_id),
    state0 AS (SELECT task_id, list_transform(ys, lambda y: 0.0::DOUBLE) AS a, list_transform(range({D}), lambda j: 0.0::DOUBLE) AS v, list_transform(range({D}), lambda j: 0.0::DOUBLE) AS w FROM packed)"""]
    for h in range(rounds):
        parts.append(f"""run{h} AS (SELECT p.task_id, curve, xs, ys, norms, n, 1::BIGINT AS i, w AS u, a, []::DOUBLE[] AS b FROM packed p JOIN state{h} s ON p.task_id = s.task_id WHERE NOT ({gone.format(h=h)})
      UNION ALL SELECT task_id, curve, xs, ys, norms, n, i + 1, [{moved}], a, list_append(b, new) FROM (SELECT *, {new} AS new FROM (SELECT *, {dot} AS xu FROM run{h} WHERE i <= n))),
    shared{h} AS (SELECT s.task_id, coalesce(r.b, s.a) AS a, CASE WHEN r.u IS NULL THEN s.v ELSE list_transform(range(1, {D + 1}), lambda j: s.v[j] + (r.u[j] - s.w[j]) / r.curve) END AS v
      FROM state{h} s LEFT JOIN (SELECT * FROM run{h} WHERE i = n + 1) r ON s.task_id = r.task_id),
    long{h} AS (SELECT task_id, j, {mixed} AS w FROM (SELECT task_id, j, v[j] AS v, avg(v[j]) OVER (PARTITION BY cluster_id, j) AS mean FROM shared{h} JOIN ({clusters}) USING (task_id), (SELECT range AS j FROM range(1, {D + 1})))),
    state{h + 1} AS (SELECT s.task_id, any_value(s.a) AS a, any_value(s.v) AS v, list(l.w ORDER BY j) AS w FROM shared{h} s JOIN long{h} l ON s.task_id = l.task_id GROUP BY s.task_id)""")
    last = f"SELECT task_id, (j - 1)::INTEGER AS coordinate, round(w, 6) + 0.0 AS x FROM long{rounds - 1}"
    if mean_from is not None:
        kept = " UNION ALL ".join(f"SELECT * FROM long{h}" for h in range(mean_from, rounds))
        last = f"SELECT task_id, (j - 1)::INTEGER AS coordinate, round(avg(w), 6) + 0.0 AS x FROM ({kept}) GROUP BY 1, 2"
    return "WITH RECURSIVE " + ", ".join(parts) + " " + last


#: Half of every label as dual: shared vectors are half the sums of points times labels, and weights half of WEIGHTS.
HALF = f"SELECT p.task_id, row_id, y, 0.5 * y AS a, 0.5 * z AS z FROM ({SCORED}) p"
HALF_PARTS = f"""SELECT sum({LAM1} * 0.25 * (w - mean) * (w - mean) + {LAM2} * 0.25 * w * w) AS penalty, 0.5 * sum(0.5 * v * 0.5 * w) AS conjugate FROM
  (SELECT w.*, v, avg(w) OVER (PARTITION BY cluster_id, w.coordinate) AS mean FROM ({WEIGHTS}) w JOIN ({SHARED}) s ON w.task_id = s.task_id AND w.coordinate = s.coordinate)"""


def _gap(value: str, conjugate: str) -> str:
    return f"""SELECT round(p + penalty, 5) AS primal, round(q + conjugate, 5) AS dual, round(p + penalty + q + conjugate, 5) AS gap FROM
      (SELECT sum({value}) AS p, sum({conjugate}) AS q FROM ({HALF})), ({HALF_PARTS})"""


def _dropped(p: float) -> str:
    return uniform_sql("'drop'", "'0'", "'0'", "'{h}'", "p.task_id::VARCHAR") + f" < {p}"


def _minibatch(rounds: int, batch: int) -> tuple[str, str]:
    """The points, and for round {h} the sampled rows of each task: a row's place in its block is its place by row_id."""
    points = f"pts AS (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY row_id) - 1 AS i, count(*) OVER (PARTITION BY task_id) AS n, list_dot_product(x, x) AS norm FROM ({SENSOR}))"
    draw = uniform_sql("'batch'", "'0'", "'{h}'", "task_id::VARCHAR", "'0'", "i::VARCHAR")
    return points, f"(SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY {draw}, i) <= {batch} AS picked FROM pts)"


def _dots(weights: str) -> str:
    return f"(SELECT p.*, z FROM {{rows}} p JOIN (SELECT q.task_id, q.row_id, sum(q.x[j] * w) AS z FROM pts q JOIN {weights} l ON q.task_id = l.task_id GROUP BY ALL) d ON p.task_id = d.task_id AND p.row_id = d.row_id)"


def _sgd(rounds: int, batch: int, eta: float) -> str:
    points, sample = _minibatch(rounds, batch)
    parts = [points, f"w0 AS (SELECT t.range AS task_id, t.range % 3 AS cluster_id, j.range AS j, 0.0::DOUBLE AS w FROM range({M}) t, range(1, {D + 1}) j)"]
    out = []
    for h in range(rounds + 1):
        parts.append(f"z{h} AS {_dots(f'w{h}').format(rows=sample.format(h=h))}")
        parts.append(f"m{h} AS (SELECT *, avg(w) OVER (PARTITION BY cluster_id, j) AS mean FROM w{h})")
        out.append(f"SELECT {h} AS round, round((SELECT sum(greatest(0.0, 1.0 - y * z)) FROM z{h}) + (SELECT sum({LAM1} * (w - mean) * (w - mean) + {LAM2} * w * w) FROM m{h}), 5) AS primal")
        if h < rounds:
            parts.append(f"g{h} AS (SELECT task_id, k.range AS j, sum(CASE WHEN picked AND y * z < 1 THEN -y * x[k.range] ELSE 0 END) * any_value(n) / count(*) FILTER (picked) AS g FROM z{h}, range(1, {D + 1}) k GROUP BY 1, 2)")
            parts.append(f"w{h + 1} AS (SELECT m.task_id, cluster_id, m.j, w - {eta} / sqrt({h + 1.0}) * (g + 2 * ({LAM1} * (w - mean) + {LAM2} * w)) AS w FROM m{h} m JOIN g{h} g ON m.task_id = g.task_id AND m.j = g.j)")
    return "WITH " + ", ".join(parts) + " " + " UNION ALL ".join(out)


def _sdca(rounds: int, batch: int, scale: float, sigma: str) -> str:
    """Stale steps of the sampled rows, scaled; sigma carries the same factor as the moves."""
    points, sample = _minibatch(rounds, batch)
    clusters, mixed = CLUSTERED
    gamma = scale / batch
    parts = [points, "a0 AS (SELECT task_id, row_id, 0.0::DOUBLE AS a FROM pts)"]
    out = []
    for h in range(rounds + 1):
        parts.append(f"v{h} AS (SELECT p.task_id, k.range AS j, sum(a * x[k.range]) AS v FROM pts p JOIN a{h} a ON p.task_id = a.task_id AND p.row_id = a.row_id, range(1, {D + 1}) k GROUP BY 1, 2)")
        parts.append(f"w{h} AS (SELECT *, {mixed} AS w FROM (SELECT v.*, cluster_id, kappa, avg(v) OVER (PARTITION BY cluster_id, j) AS mean FROM v{h} v JOIN ({clusters}) USING (task_id)))")
        parts.append(f"z{h} AS (SELECT d.*, a FROM {_dots(f'w{h}').format(rows=sample.format(h=h))} d JOIN a{h} a ON d.task_id = a.task_id AND d.row_id = a.row_id)")
        parts.append(f"o{h} AS (SELECT (SELECT sum(greatest(0.0, 1.0 - y * z)) FROM z{h}) + (SELECT sum({LAM1} * (w - c) * (w - c) + {LAM2} * w * w) FROM (SELECT *, avg(w) OVER (PARTITION BY cluster_id, j) AS c FROM w{h})) AS p, "
                     f"(SELECT sum(-y * a) FROM z{h}) + (SELECT 0.5 * sum(v * w) FROM w{h}) AS q)")  # fmt: skip
        out.append(f"SELECT 'sdca' AS run, 0 AS \"outer\", {h} AS round, round(p, 5) AS primal, round(q, 5) AS dual, round(p + q, 5) AS gap FROM o{h}")
        if h < rounds:
            step = HINGE.format(a="a", y="y", xu="z", q=f"({sigma} * {gamma} * kappa * norm)")
            parts.append(f"a{h + 1} AS (SELECT z.task_id, row_id, CASE WHEN picked THEN a + {gamma} * ({step} - a) ELSE a END AS a FROM z{h} z JOIN ({clusters}) USING (task_id))")
    return "WITH " + ", ".join(parts) + " " + " UNION ALL ".join(out)


#: The closed form of the largest ratio for clusters of seven tasks at most.
SIGMA = f"(1 / ((1 - 1.0 / 7) * {LAM2} / {LAM1 + LAM2} + 1.0 / 7))"
NODES = f"""SELECT task_id, round, 0.25 + 0.75 * {uniform_sql("'speed'", "'0'", "task_id::VARCHAR")} AS speed, 0.5 + {uniform_sql("'net'", "'0'", "task_id::VARCHAR")} AS net
  FROM (SELECT t.range AS task_id, r.range::INTEGER AS round FROM range({M}) t, range(2) r)"""

ORACLES: dict[str, str] = {
    "tasks_sensor": _sums(f"SELECT task_id, label, list_sum(x) AS s FROM ({SENSOR_PLANTED})", 65),
    "planted_sensor_labels": f"SELECT task_id, count(*) AS n, sum(label)::BIGINT AS balance FROM ({SENSOR_PLANTED}) GROUP BY task_id",
    "tasks_nation": _sums(f"SELECT task_id, label, list_sum(x) AS s FROM ({NATION_PLANTED})", 16),
    "tasks_customer": _sums(f"SELECT task_id, label, list_sum(x) AS s FROM ({ORDER_ROWS.format(task='o_custkey')})", 16),
    "tasks_doc_language": _sums(LANGUAGE_ROWS, 284),
    "tasks_doc_quality": _sums(QUALITY_ROWS, 6),
    "tasks_host": _sums(HOST_ROWS, 29),
    "tasks_event_windows": _sums(EVENT_ROWS, 40),
    "hash_text_features": """WITH c AS (SELECT doc_id, list_transform(string_split(low, ''), lambda s: unicode(s)::BIGINT) AS u, length(low) AS n FROM (SELECT doc_id, lower(coalesce(text, '')) AS low FROM documents)),
      g AS (SELECT doc_id, n, unnest(list_transform(range(1, n), lambda i: ((u[i] % 256) * 31 + u[i + 1]) % 256)) AS bucket FROM c WHERE n >= 2)
      SELECT doc_id, bucket::INTEGER AS bucket, round(count(*) / any_value(n - 1), 6) AS share FROM g GROUP BY doc_id, bucket""",
    "three_rounds_cluster": _rounds(3, HINGE, CLUSTERED, 3.0),
    "independent_rounds": _rounds(2, SQUARED, ALONE, 1.0),
    "dropping_weights": _rounds(3, HINGE, CLUSTERED, 3.0, _dropped(0.5)),
    "averaged_iterate": _rounds(3, HINGE, CLUSTERED, 3.0, mean_from=1),
    "drop_round": f"""SELECT r.range::INTEGER AS round, task_id, {uniform_sql("'drop'", "'0'", "'0'", "r.range::VARCHAR", "task_id::VARCHAR")} < 0.5 AS dropped,
      (CASE WHEN {uniform_sql("'drop'", "'0'", "'0'", "r.range::VARCHAR", "task_id::VARCHAR")} < 0.5 THEN 0 ELSE n END)::BIGINT AS steps FROM (SELECT task_id, count(*) AS n FROM ({SENSOR}) GROUP BY 1), range(3) r""",
    "clock_round": f"SELECT round, task_id, steps < 1 AS dropped, greatest(steps, 0)::BIGINT AS steps FROM (SELECT *, floor((30.0 - net * 20.0) * speed / 1.0) AS steps FROM ({NODES}))",
    "sgd_rounds": _sgd(3, 8, 0.05),
    "sdca_minibatch_rounds": _sdca(3, 8, 2.0, SIGMA),
    "duality_gap_hinge": _gap("greatest(0.0, 1.0 - y * z)", "-y * a"),
    "duality_gap_squared": _gap("0.5 * (z - y) * (z - y)", "0.5 * a * a - y * a"),
    "duality_gap_smooth_hinge": _gap("CASE WHEN 1.0 - y * z <= 0 THEN 0.0 WHEN 1.0 - y * z >= 0.5 THEN 1.0 - y * z - 0.25 ELSE (1.0 - y * z) * (1.0 - y * z) END", "-y * a + 0.25 * a * a"),
    "subproblem_value": f"""SELECT p.task_id, round(linear + 0.5 * 3.0 * kappa * square, 5) AS value FROM
      (SELECT task_id, sum(-y * (0.75 * y) + 0.25 * y * z) AS linear FROM ({HALF}) GROUP BY 1) p JOIN (SELECT task_id, sum(0.25 * v * 0.25 * v) AS square FROM ({SHARED}) GROUP BY 1) s ON p.task_id = s.task_id
      JOIN ({CLUSTERED[0]}) c ON p.task_id = c.task_id""",
    "tasks_supplier": _summary(f"SELECT l_suppkey AS task_id, {SUPPLIER_X} AS x, CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE -1.0 END AS label FROM lineitem JOIN part ON l_partkey = p_partkey", 10),
    "tasks_conversation": _summary(
        f"SELECT conv_id AS task_id, {CONVERSATION_X} AS x, CASE WHEN role = 'assistant' THEN 1.0 ELSE -1.0 END AS label FROM (SELECT *, coalesce(text, '') AS t, greatest(length(coalesce(text, '')), 1) AS n FROM conversations)", 5
    ),
    "task_sizes": f"SELECT task_id, count(*) AS n, count(*) FILTER (label > 0) AS positives FROM ({NATION_ROWS}) GROUP BY task_id",
    "task_imbalance": """WITH n AS (SELECT o_custkey AS task_id, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1), r AS (SELECT *, row_number() OVER (ORDER BY n, task_id) AS r FROM n)
      SELECT count(*) AS tasks, sum(n)::BIGINT AS points, min(n) AS least, quantile_cont(n, 0.5) AS median, max(n) AS most, round(max(n) / quantile_cont(n, 0.5), 6) AS most_over_median,
        round(2.0 * sum(n * r) / (count(*) * sum(n)) - (count(*) + 1) / count(*), 6) AS gini FROM r""",
    "split_75_25": f"SELECT task_id, split, count(*) AS n, sum(row_id)::BIGINT AS rows FROM ({SPLIT.replace('ROWS', f'({NATION_ROWS})')}) GROUP BY ALL",
    "folds_ntile5": f"""SELECT task_id, fold, count(*) AS n, sum(row_id)::BIGINT AS rows FROM (SELECT *, (ntile(5) OVER (PARTITION BY task_id ORDER BY {uniform_sql("'split'", "'1'", "'0'", "task_id::VARCHAR", "row_id::VARCHAR")}, row_id) - 1)::INTEGER AS fold
      FROM ({NATION_ROWS})) GROUP BY ALL""",
    "skew_subsample": f"SELECT task_id, count(*) AS n, sum(row_id)::BIGINT AS rows FROM ({NATION_ROWS}) WHERE {uniform_sql("'keep'", "'0'", "task_id::VARCHAR", "row_id::VARCHAR")} < pow(0.5, task_id % 4) GROUP BY task_id",
    "stratified_sample": f"""SELECT task_id, count(*) AS n, sum(row_id)::BIGINT AS rows FROM (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY {uniform_sql("'pick'", "'0'", "task_id::VARCHAR", "row_id::VARCHAR")}, row_id) AS p
      FROM ({NATION_ROWS})) WHERE p <= 30 GROUP BY task_id""",
    "bootstrap_counts": f"""SELECT ({' + '.join(f'(u >= {s!r})::INT' for s in poisson_steps())})::INTEGER AS weight, count(*) AS n
      FROM (SELECT {uniform_sql("'boot'", "'0'", "task_id::VARCHAR", "row_id::VARCHAR")} AS u FROM ({NATION_ROWS})) GROUP BY 1""",
    "portable_uniform": f"SELECT o_orderkey, round({uniform_sql("'demo'", "'7'", "o_orderkey::VARCHAR")}, 6) AS u FROM orders",
    "pack_blocks": f"""SELECT task_id, block_id, count(*)::INTEGER AS n, min(row_id) AS first_row, round(sum(list_dot_product(x, x)), 6) AS norms FROM
      (SELECT *, floor({uniform_sql("'block'", "'0'", "task_id::VARCHAR", "row_id::VARCHAR")} * ceil(count(*) OVER (PARTITION BY task_id) / 8))::INTEGER AS block_id FROM ({SENSOR})) GROUP BY 1, 2""",
    "standardize_train_only": f"""WITH s AS ({SPLIT.replace('ROWS', f'({SENSOR})')}), long AS (SELECT split, c.range::INTEGER AS coordinate, x[c.range + 1] AS x FROM s, range({D}) c),
      m AS (SELECT coordinate, avg(x) AS mean, stddev_samp(x) AS sd FROM long WHERE split = 'train' GROUP BY 1)
      SELECT split, coordinate, round(avg((x - mean) / sd), 5) + 0.0 AS mean, round(stddev_samp((x - mean) / sd), 5) AS sd FROM long JOIN m USING (coordinate) GROUP BY 1, 2""",
    "mix_independent": _mix(None),
    "mix_cluster": _mix(CLUSTERS),
    "mix_mean": _mix(f"SELECT range AS task_id, 0 AS cluster_id FROM range({M})"),
    "mix_known_region": _mix(REGIONS, REGION_SHARED),
    "cluster_centroids": f"SELECT cluster_id, coordinate, round(avg(v), 6) AS x FROM ({SHARED}) JOIN ({CLUSTERS}) USING (task_id) GROUP BY 1, 2",
    "kappa_by_task": f"SELECT task_id, round(0.5 * ((1 - 1.0 / c) / {LAM1 + LAM2} + 1.0 / (c * {LAM2})), 6) AS kappa FROM (SELECT c_custkey::BIGINT AS task_id, count(*) OVER (PARTITION BY c_nationkey) AS c FROM customer)",
    "sigma_cluster_rules": f"""WITH c AS (SELECT max(n) AS c, sum(n) AS m FROM (SELECT count(*) AS n FROM customer GROUP BY c_nationkey)),
      s AS (SELECT 1 / ((1 - 1.0 / c) * {LAM2} / {LAM1 + LAM2} + 1.0 / c) AS s, m FROM c WHERE m > 0)
      SELECT 'spectral' AS rule, round(s, 6) AS sigma FROM s UNION ALL SELECT 'gershgorin', round(s, 6) FROM s UNION ALL SELECT 'trace', m::DOUBLE FROM s""",
    "gram_matrix": f"SELECT i.range::INTEGER AS i, j.range::INTEGER AS j, round(sum(x[i.range + 1] * x[j.range + 1]), 5) AS value FROM ({SENSOR}), range({D}) i, range({D}) j WHERE i.range <= j.range GROUP BY 1, 2",
    "task_similarity_topk": f"""WITH v AS (SELECT task_id, list(v ORDER BY coordinate) AS v FROM ({SHARED}) GROUP BY 1)
      SELECT task_id, other, rank::INTEGER AS rank, round(cosine, 6) AS cosine FROM (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY round(cosine, 9) DESC, other) AS rank FROM
        (SELECT a.task_id, b.task_id AS other, list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v) * list_dot_product(b.v, b.v)) AS cosine FROM v a JOIN v b ON a.task_id <> b.task_id)) WHERE rank <= 3""",
    "graph_laplacian_edges": f"""WITH t AS ({REGIONS}), e AS (SELECT a.task_id AS i, b.task_id AS j FROM t a JOIN t b ON a.cluster_id = b.cluster_id AND a.task_id <> b.task_id)
      SELECT i, j, -1.0 AS value FROM e UNION ALL SELECT i, i, count(*)::DOUBLE FROM e GROUP BY i""",
    "local_pass_hinge": _local(HINGE),
    "local_pass_squared": _local(SQUARED),
    "local_pass_smooth_hinge": _local(SMOOTH),
    "local_pass_absolute": _local(ABSOLUTE),
    "budgeted_pass": _local(HINGE, 7),
    "local_pass_arrow": f"SELECT task_id, steps, coordinate, round(u / 1.5, 6) AS dv FROM ({_local(HINGE).replace('round(u[c.range + 1], 6) AS u', 'u[c.range + 1] AS u')})",
    "first_round_cluster": _first_round(1.0),
    "gamma_half_round": _first_round(0.5),
    "task_error": f"SELECT task_id, count(*) AS n_test, round(avg(CASE WHEN (CASE WHEN z >= 0 THEN 1.0 ELSE -1.0 END) <> y THEN 1.0 ELSE 0.0 END), 6) AS error FROM ({SCORED}) GROUP BY task_id",
    "mean_task_error": f"SELECT round(avg(e), 6) AS error, count(*) AS tasks FROM (SELECT task_id, avg(CASE WHEN (CASE WHEN z >= 0 THEN 1.0 ELSE -1.0 END) <> y THEN 1.0 ELSE 0.0 END) AS e FROM ({SCORED}) GROUP BY task_id)",
    "primal_loss_hinge": _loss("greatest(0.0, 1.0 - y * z)"),
    "primal_loss_smooth_hinge": _loss("CASE WHEN 1.0 - y * z <= 0 THEN 0.0 WHEN 1.0 - y * z >= 0.5 THEN 1.0 - y * z - 0.25 ELSE (1.0 - y * z) * (1.0 - y * z) END"),
    "primal_loss_squared": _loss("0.5 * (z - y) * (z - y)"),
    "primal_loss_logistic": _loss("ln(1 + exp(-y * z))"),
    "primal_loss_absolute": _loss("abs(z - y)"),
    "penalty_cluster": f"SELECT round(sum({LAM1} * (w - mean) * (w - mean) + {LAM2} * w * w), 5) AS penalty FROM (SELECT *, avg(w) OVER (PARTITION BY cluster_id, coordinate) AS mean FROM ({WEIGHTS}))",
    "simulated_time_wifi": _time(10.0),
    "simulated_time_lte": _time(100.0),
    "simulated_time_3g": _time(1000.0),
    "straggler_report": f"SELECT round, max(flops) AS most, quantile_cont(flops, 0.5) AS median, round(max(flops) / quantile_cont(flops, 0.5), 6) AS ratio FROM ({LOG}) WHERE NOT dropped GROUP BY round",
    "assumption_report": f"""SELECT round(max(p), 6) AS p_max, round(max(theta), 6) AS theta_max, round(max(p) + (1 - max(p)) * max(theta), 6) AS theta_bar FROM
      (SELECT task_id, avg(CASE WHEN dropped THEN 1.0 ELSE 0.0 END) AS p, avg(theta) FILTER (NOT dropped) AS theta FROM ({LOG}) GROUP BY task_id)""",
    "communication_volume": f"SELECT run, sum(comm_elems)::BIGINT AS comm_elems, sum(flops) AS flops, max(round) AS last_round FROM ({LOG}) GROUP BY run",
    "time_to_target": f"SELECT 'x' AS run, min(sim_time) AS sim_time, min(round) AS rounds FROM ({_time(10.0)}) WHERE 1.0 / (round + 1) <= 0.26",
    "rounds_bounds": f"""WITH t AS (SELECT sum(n)::DOUBLE AS n, 3.0 * {0.5 / LAM2} * sum(n * n)::DOUBLE AS a FROM (SELECT count(*) AS n FROM orders GROUP BY o_custkey)),
      f AS (SELECT *, ceil(greatest(0.0, 1 + ln(2 * n * n * n / (4 * a)) / 0.5) + 16 * a / (0.5 * n * n * 1e-3)) AS f FROM t WHERE n > 0)
      SELECT ceil(ln(n / 1e-3) / (0.5 * 0.01))::BIGINT AS smooth, f::BIGINT AS lipschitz_first, (f + ceil(2 / 0.5 * greatest(1.0, 2 * a / (n * n * 1e-3))))::BIGINT AS lipschitz_total FROM f""",
    "trial_summary": """SELECT model, round(avg(error), 6) AS mean, round(stddev_samp(error) / sqrt(count(*)), 6) AS se, count(*) AS trials FROM
      (SELECT event_type AS model, user_id % 10 AS trial, avg(value) AS error FROM events GROUP BY 1, 2) GROUP BY model""",
}
