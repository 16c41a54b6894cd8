"""DuckDB SQL of whole fits: the first iterations of an optimiser with a line search, unrolled into common table expressions.

Everything is a table: features (row_id, f, v) as ex, labels (row_id, y) as yy, parameters and gradients by f. It shares no code
with the learners and serves as the other side of their comparison. A search takes EXPANSIONS or EVALUATIONS at most."""

from __future__ import annotations

EXPANSIONS, EVALUATIONS, HALVINGS = 6, 8, 4

TOKENS = r"list_filter(regexp_split_to_array(lower(coalesce({0}, '')), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> '')"
SOFT = "ln(1 + exp(-abs({z}))) + greatest(-({z}), 0) + CASE WHEN y = 0 THEN {z} ELSE 0 END"


def _slot(text: str, m: int) -> str:
    return f"CAST(('0x' || substr(md5({text}), 1, 8))::BIGINT % {m} AS BIGINT)"


def _hashed(rows: str, m: int) -> str:
    """ex and yy of (row_id, y, words) rows: 1 + ln of counts by bucket, of length 1, and the constant m."""
    return f"""raw AS MATERIALIZED ({rows}),
yy AS MATERIALIZED (SELECT row_id, y FROM raw),
cnt AS (SELECT row_id, {_slot('t', m)} AS f, count(*) AS c FROM (SELECT row_id, unnest(words) AS t FROM raw) GROUP BY 1, 2),
nrm AS (SELECT row_id, sqrt(sum((1 + ln(c)) * (1 + ln(c)))) AS size FROM cnt GROUP BY 1),
ex AS MATERIALIZED (SELECT row_id, f, (1 + ln(c)) / size AS v FROM cnt JOIN nrm USING (row_id) UNION ALL SELECT row_id, {m}, 1 FROM yy)"""


def features(name: str, m: int | None = None) -> str:
    """The expressions that define ex and yy of a workload."""
    big = m or 1 << 20
    if name == "w1":
        return """yy AS MATERIALIZED (SELECT vec_id AS row_id, CASE WHEN label < 5 THEN 1 ELSE 0 END AS y FROM embeddings),
ex AS MATERIALIZED (SELECT vec_id AS row_id, unnest(range(0, 65)) AS f, CAST(unnest(list_append(CAST(embedding AS DOUBLE[]), 1)) AS DOUBLE) AS v FROM embeddings)"""
    if name == "w2":
        return _hashed(f"SELECT doc_id AS row_id, CASE WHEN lang = 'en' THEN 1 ELSE 0 END AS y, {TOKENS.format('text')} AS words FROM documents", m or 1024)
    if name == "w3":
        url = TOKENS.format("regexp_extract(url, '://(.*)', 1)")
        page = TOKENS.format("regexp_replace(html, '<[^>]*>', ' ', 'g')")
        return _hashed(f"SELECT page_id AS row_id, CASE WHEN starts_with(url, 'http://') THEN 1 ELSE 0 END AS y, list_transform({url}, lambda t: 'u:' || t) || {page} AS words FROM pages", big)
    if name == "w4":
        return _hashed(f"""SELECT doc_id AS row_id, CASE WHEN quality = 1 THEN 1 ELSE 0 END AS y,
  w || list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) || ['source:' || source, 'lang:' || lang] AS words
  FROM (SELECT *, {TOKENS.format('text')} AS w FROM documents JOIN labels USING (doc_id))""", big)
    if name == "w5":
        combos = [("part", ["l_partkey"]), ("supp", ["l_suppkey"]), ("cust", ["o_custkey"]), ("brand", ["p_brand"]), ("type", ["p_type"]), ("flag", ["l_returnflag"]), ("status", ["l_linestatus"]), ("month", ["mon"]), ("nation", ["c_nationkey"]), ("home", ["s_nationkey"]), ("priority", ["o_orderpriority"]), ("segment", ["c_mktsegment"]), ("brand-month", ["p_brand", "mon"]), ("nations", ["c_nationkey", "s_nationkey"]), ("part-supp", ["l_partkey", "l_suppkey"])]
        slots = ", ".join(_slot("'" + n + "' || " + " || ".join(f"'|' || {c}" for c in cols), big) for n, cols in combos)
        return f"""raw AS MATERIALIZED (SELECT row_number() OVER () AS row_id, CASE WHEN l_quantity > 7 THEN 1 ELSE 0 END AS y, list_append(list_distinct([{slots}]), {big}) AS fs
  FROM (SELECT *, month(l_shipdate) AS mon FROM lineitem) JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey),
yy AS MATERIALIZED (SELECT row_id, y FROM raw),
ex AS MATERIALIZED (SELECT row_id, unnest(fs) AS f, 1::DOUBLE AS v FROM raw)"""
    if name == "w9":
        from .queries import PLANTED

        return f"""rows9 AS MATERIALIZED (WITH {PLANTED.strip().removeprefix('WITH ')} SELECT row_number() OVER () AS row_id, * FROM d),
yy AS MATERIALIZED (SELECT row_id, y FROM rows9),
ex AS MATERIALIZED (SELECT row_id, unnest([0, 1, 2, 3, 4]) AS f, CAST(unnest([x1, x2, x3, x4, 1]) AS DOUBLE) AS v FROM rows9)"""
    raise ValueError(name)


class Unrolled:
    """SQL text of a trace (k, loss, grad_norm, alpha, n_eval) of so many iterations."""

    def __init__(self, base: str, lam: float, theta: float, method: str, search: str, iterations: int, degree: int = 5, restart: float | None = None):
        self.ctes, self.lam, self.theta, self.method, self.search, self.degree = [base], lam, theta, method, search, degree
        self.restart = restart if restart is not None else {"taylor": 0.2, "wolfe": 1.0}[search]
        self.add("nn", "SELECT count(*)::DOUBLE AS n FROM yy")
        self.add("p0", "SELECT f, 0::DOUBLE AS w0 FROM (SELECT DISTINCT f FROM ex)")
        self.add("z0", "SELECT row_id, y, 0::DOUBLE AS z FROM yy")
        self.graded(0)
        for k in range(iterations):
            self.aimed(k)
            (self.taylor if search == "taylor" else self.wolfe)(k)
            self.moved(k)
            self.graded(k + 1)
        rows = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, round(loss, 7) + 0.0 AS loss, round(gn, 6) + 0.0 AS grad_norm, {f'round(a{k - 1}.alpha, 4) + 0.0' if k else '0::DOUBLE'} AS alpha, CAST({f'a{k - 1}.n_eval' if k else '0'} AS INTEGER) AS n_eval FROM f{k}{f', a{k - 1}' if k else ''}" for k in range(iterations + 1))
        self.text = "WITH " + ",\n".join(self.ctes) + "\n" + rows

    def add(self, name: str, body: str) -> str:
        self.ctes.append(f"{name} AS MATERIALIZED ({body})")
        return name

    def graded(self, k: int) -> None:
        """b{k}: parameters with the gradient at iterate k; f{k}: loss and norm."""
        self.add(f"g{k}", f"SELECT f, sum(v * s) AS g FROM ex JOIN (SELECT row_id, 1 / (1 + exp(-z)) - y AS s FROM z{k}) USING (row_id) GROUP BY f")
        self.add(f"b{k}", f"SELECT p{k}.*, g / n + {self.lam} * w{k} AS g{k} FROM p{k} JOIN g{k} USING (f), nn")
        self.add(f"f{k}", f"SELECT (SELECT avg({SOFT.format(z='z')}) FROM z{k}) + {self.lam / 2} * sum(w{k} * w{k}) AS loss, sqrt(sum(g{k} * g{k})) AS gn FROM b{k}")

    def aimed(self, k: int) -> None:
        """d{k}: with the direction d and the ray r; m{k}: margins along it; s{k}: first step, slope and the penalty's sums."""
        if self.method == "lbfgs":
            at = self.add(f"q{k}_0", f"SELECT *, g{k} AS q FROM b{k}")
            s, y = (lambda j, c=c: f"({c}{j + 1} - {c}{j})" for c in "wg")
            for j in reversed(range(k)):
                self.add(f"u{k}_{j}", f"SELECT sum({s(j)} * q) / sum({s(j)} * {y(j)}) AS u FROM {at}")
                at = self.add(f"q{k}_{k - j}", f"SELECT {at}.* REPLACE (q - u * {y(j)} AS q) FROM {at}, u{k}_{j}")
            if k:
                at = self.add(f"q{k}_s", f"SELECT {at}.* REPLACE (q * (SELECT sum({s(k - 1)} * {y(k - 1)}) / sum({y(k - 1)} * {y(k - 1)}) FROM {at}) AS q) FROM {at}")
            for j in range(k):
                self.add(f"t{k}_{j}", f"SELECT u - (SELECT sum({y(j)} * q) / sum({s(j)} * {y(j)}) FROM {at}) AS t FROM u{k}_{j}")
                at = self.add(f"r{k}_{j}", f"SELECT {at}.* REPLACE (q + t * {s(j)} AS q) FROM {at}, t{k}_{j}")
            self.add(f"e{k}", f"SELECT * EXCLUDE (q), -q AS d{k} FROM {at}")
        elif self.method == "ncg" and k:
            self.add(f"h{k}", f"SELECT sum(g{k} * g{k}) AS gg, sum(g{k} * g{k - 1}) AS mix, sum(g{k - 1} * g{k - 1}) AS old FROM b{k}")
            self.add(f"e{k}", f"SELECT b{k}.*, -g{k} + CASE WHEN abs(mix) >= {self.restart} * gg THEN 0 ELSE greatest(0, (gg - mix) / old) END * d{k - 1} AS d{k} FROM b{k}, h{k}")
        else:
            self.add(f"e{k}", f"SELECT *, -g{k} AS d{k} FROM b{k}")
        size = f"sqrt(sum(d{k} * d{k}) OVER ())" if self.method != "lbfgs" and self.search == "taylor" else "1"
        self.add(f"d{k}", f"SELECT *, d{k} / {size} AS r{k} FROM e{k}")
        self.add(f"m{k}", f"SELECT z{k}.*, q FROM z{k} JOIN (SELECT row_id, sum(v * r{k}) AS q FROM ex JOIN d{k} USING (f) GROUP BY row_id) USING (row_id)")
        first = "1" if self.method == "lbfgs" or not k else f"(SELECT a{k - 1}.alpha * s{k - 1}.slope FROM a{k - 1}, s{k - 1}) / sum(g{k} * r{k})"
        self.add(f"s{k}", f"SELECT {first}::DOUBLE AS alpha, sum(g{k} * r{k}) AS slope, sum(w{k} * w{k}) AS ww, sum(w{k} * r{k}) AS wp, sum(r{k} * r{k}) AS pp FROM d{k}")

    def taylor(self, k: int) -> None:
        lam, d = self.lam, self.degree
        terms = [SOFT.format(z="z"), "q * (s - y)", "q * q * s * (1 - s) / 2", "pow(q, 3) * s * (1 - s) * (1 - 2 * s) / 6", "pow(q, 4) * s * (1 - s) * (1 - 6 * s * (1 - s)) / 24", "pow(q, 5) * s * (1 - s) * (1 - 2 * s) * (1 - 12 * s * (1 - s)) / 120"][: d + 1]
        extra = [f" + {lam / 2} * (any_value(ww) + 2 * any_value(alpha) * any_value(wp) + any_value(alpha) * any_value(alpha) * any_value(pp))", f" + {lam} * (any_value(wp) + any_value(alpha) * any_value(pp))", f" + {lam / 2} * any_value(pp)"]
        sums = ", ".join(f"avg({t}){extra[j] if j < 3 else ''} AS c{j}" for j, t in enumerate(terms))
        value = lambda t: " + ".join(f"c{j} * pow({t}, {j})" for j in range(d + 1))
        d1 = lambda t: " + ".join(f"{j} * c{j} * pow({t}, {j - 1})" for j in range(1, d + 1))
        d2 = lambda t: " + ".join(f"{j * (j - 1)} * c{j} * pow({t}, {j - 2})" for j in range(2, d + 1))
        size = " + ".join(f"{j} * abs(c{j}) * pow(abs(t), {j - 1})" for j in range(1, d + 1))
        self.add(f"x{k}_0", f"SELECT alpha, false AS done, 0 AS n_eval FROM s{k}")
        for j in range(EXPANSIONS):
            now = f"x{k}_{j}"
            self.add(f"c{k}_{j}", f"SELECT alpha, done, n_eval, {sums} FROM (SELECT y, q, z + x.alpha * q AS z, 1 / (1 + exp(-(z + x.alpha * q))) AS s, x.alpha, done, n_eval, ww, wp, pp FROM m{k}, {now} x, s{k}) GROUP BY alpha, done, n_eval")
            self.add(f"n{k}_{j}", f"SELECT *, list_reduce([0::DOUBLE, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10], lambda t, i: t - ({d1('t')}) / ({d2('t')})) AS t FROM c{k}_{j}")
            good = f"coalesce(isfinite(t) AND alpha + t > 0 AND ({d2('t')}) > 0 AND ({value('t')}) <= c0 + 1e-14 * abs(c0) AND abs({d1('t')}) <= 1e-13 * greatest(1, {size}), false)"
            self.add(f"o{k}_{j}", f"SELECT *, CASE WHEN {good} THEN t WHEN c2 > 0 THEN -c1 / (2 * c2) ELSE 'inf'::DOUBLE END AS best FROM n{k}_{j}")
            self.add(f"v{k}_{j}", f"SELECT *, CASE WHEN isinf(best) AND c1 < 0 THEN 9 * alpha WHEN isinf(best) OR alpha + best <= 0 THEN -alpha / 2 WHEN alpha + best > 10 * alpha THEN 9 * alpha ELSE best END AS go FROM o{k}_{j}")
            done = f"(go = best AND (abs(c{d} * pow(go, {d})) <= {self.theta} * abs({value('go')}) OR abs(go) <= 1e-12 * greatest(1, alpha + go)))"
            self.add(f"x{k}_{j + 1}", f"SELECT CASE WHEN done THEN alpha ELSE alpha + go END AS alpha, done OR {done} AS done, n_eval + CASE WHEN done THEN 0 ELSE 1 END AS n_eval FROM v{k}_{j}")
        loss = lambda i: f"avg({SOFT.format(z=f'(z + x.alpha / {2 ** i} * q)')}) + {lam / 2} * (any_value(ww) + 2 * any_value(x.alpha) / {2 ** i} * any_value(wp) + any_value(x.alpha) * any_value(x.alpha) / {4 ** i} * any_value(pp))"
        self.add(f"l{k}", f"SELECT any_value(x.alpha) AS alpha, any_value(x.n_eval) AS n_eval, any_value(slope) AS slope, {', '.join(f'{loss(i)} AS l{i}' for i in range(HALVINGS))} FROM m{k}, x{k}_{EXPANSIONS} x, s{k}")
        self.add(f"a{k}", f"SELECT CASE {' '.join(f'WHEN l{i} <= loss + 1e-4 * l.alpha / {2 ** i} * slope + 1e-14 * abs(loss) THEN l.alpha / {2 ** i}' for i in range(HALVINGS))} END AS alpha, n_eval FROM l{k} l, f{k}")

    def wolfe(self, k: int) -> None:
        lam = self.lam
        self.add(f"x{k}_0", f"SELECT alpha AS a, 0::DOUBLE AS la, loss AS lf, slope AS ld, NULL::DOUBLE AS ha, NULL::DOUBLE AS hf, NULL::DOUBLE AS hd, 0 AS n_eval, false AS done, NULL::DOUBLE AS best, NULL::DOUBLE AS bf, loss AS f0, slope AS d0, ww, wp, pp FROM s{k}, f{k}")
        for j in range(EVALUATIONS):
            self.add(f"c{k}_{j}", f"SELECT avg({SOFT.format(z='z')}) + {lam / 2} * any_value(ww + 2 * a * wp + a * a * pp) AS f, avg(q * (1 / (1 + exp(-z)) - y)) + {lam} * any_value(wp + a * pp) AS d FROM (SELECT y, q, z + a * q AS z, a, ww, wp, pp FROM m{k}, x{k}_{j})")
            self.add(f"x{k}_{j + 1}", bracketed(f"x{k}_{j}, c{k}_{j}", "f0, d0, ww, wp, pp"))
        self.add(f"a{k}", f"SELECT best AS alpha, n_eval FROM x{k}_{EVALUATIONS}")

    def moved(self, k: int) -> None:
        self.add(f"p{k + 1}", f"SELECT d{k}.*, w{k} + alpha * r{k} AS w{k + 1} FROM d{k}, a{k}")
        self.add(f"z{k + 1}", f"SELECT row_id, y, z + alpha * q AS z FROM m{k}, a{k}")


def bracketed(source: str, kept: str) -> str:
    """One evaluation (f, d at a) of the search for the strong Wolfe conditions, as a step of its state."""
    cubic = """(CASE WHEN (e * e - ld2 * rd) >= 0 AND (rd - ld2 + 2 * sqrt(greatest(e * e - ld2 * rd, 0))) <> 0
  THEN ra - (ra - la2) * (rd + sqrt(greatest(e * e - ld2 * rd, 0)) - e) / (rd - ld2 + 2 * sqrt(greatest(e * e - ld2 * rd, 0))) END)"""
    return f"""SELECT CASE WHEN done THEN a WHEN ha IS NULL THEN 2 * a WHEN {cubic} > la2 + 0.1 * (ra - la2) AND {cubic} < ra - 0.1 * (ra - la2) THEN {cubic} ELSE la2 + (ra - la2) / 2 END AS a,
  la, lf, ld, ha, hf, hd, n_eval, done, best, bf, {kept}
FROM (SELECT *, ld2 + rd - 3 * (rf - lf2) / (ra - la2) AS e FROM (SELECT *, least(la, ha) AS la2, greatest(la, ha) AS ra,
  CASE WHEN la < ha THEN lf ELSE hf END AS lf2, CASE WHEN la < ha THEN hf ELSE lf END AS rf, CASE WHEN la < ha THEN ld ELSE hd END AS ld2, CASE WHEN la < ha THEN hd ELSE ld END AS rd
FROM (SELECT a, {kept}, done OR (down AND flat) AS done, n_eval + CASE WHEN done THEN 0 ELSE 1 END AS n_eval,
  CASE WHEN done THEN best WHEN down AND (flat OR bf IS NULL OR f < bf) THEN a ELSE best END AS best, CASE WHEN done THEN bf WHEN down AND (flat OR bf IS NULL OR f < bf) THEN f ELSE bf END AS bf,
  CASE move WHEN 'turn' THEN greatest(la, a) WHEN 'on' THEN a ELSE la END AS la, CASE WHEN move = 'on' OR (move = 'turn' AND a >= la) THEN f ELSE lf END AS lf, CASE WHEN move = 'on' OR (move = 'turn' AND a >= la) THEN d ELSE ld END AS ld,
  CASE move WHEN 'turn' THEN least(la, a) WHEN 'close' THEN a ELSE ha END AS ha, CASE WHEN move = 'close' OR (move = 'turn' AND a < la) THEN f WHEN move = 'turn' THEN lf ELSE hf END AS hf, CASE WHEN move = 'close' OR (move = 'turn' AND a < la) THEN d WHEN move = 'turn' THEN ld ELSE hd END AS hd
FROM (SELECT *, CASE WHEN done OR (down AND flat) THEN 'none' WHEN NOT down OR f >= lf THEN 'close' WHEN d * (coalesce(ha, 'inf'::DOUBLE) - a) >= 0 THEN 'turn' ELSE 'on' END AS move
FROM (SELECT *, f <= f0 + 1e-4 * a * d0 AS down, abs(d) <= 0.9 * abs(d0) AS flat FROM {source})))))"""


def trace(name: str, method: str, search: str, lam: float, theta: float, iterations: int = 3, m: int | None = None, **options) -> str:
    return Unrolled(features(name, m), lam, theta, method, search, iterations, **options).text


def solve(features: list[str], target: str, base: str, source: str) -> str:
    """Least squares weights from the normal equations by elimination, one table for each pivot."""
    m = len(features)
    cols = [*features, target]
    text = f"{base}, n0 AS (SELECT {', '.join(f'avg({a} * {b}) AS a{i}_{j}' for i, a in enumerate(features) for j, b in enumerate(cols))} FROM {source})"
    for k in range(m):
        cell = lambda i, j, k=k: f"a{k}_{j} / a{k}_{k}" if i == k else f"a{i}_{j} - a{i}_{k} * a{k}_{j} / a{k}_{k}"
        text += f", n{k + 1} AS (SELECT {', '.join(f'{cell(i, j)} AS a{i}_{j}' for i in range(m) for j in range(m + 1))} FROM n{k})"
    return f"{text} SELECT {', '.join(f'round(a{i}_{m}, 6) + 0.0 AS w{i + 1}' for i in range(m))} FROM n{m}"


def bracket(firsts: list[float], evaluations: int = 16) -> str:
    """Wolfe searches on the worked function from several first steps, with a curvature constant of 0.1."""
    phi, slope = "a * exp(a) + exp(4 - a)", "(1 + a) * exp(a) - exp(4 - a)"
    step = bracketed("(SELECT *, {0} AS f, {1} AS d FROM x{{0}})".format(phi, slope), "first, f0, d0").replace("0.9 * abs(d0)", "0.1 * abs(d0)")
    text = f"WITH x0 AS (SELECT first, first AS a, 0::DOUBLE AS la, exp(4::DOUBLE) AS lf, 1 - exp(4::DOUBLE) AS ld, NULL::DOUBLE AS ha, NULL::DOUBLE AS hf, NULL::DOUBLE AS hd, 0 AS n_eval, false AS done, NULL::DOUBLE AS best, NULL::DOUBLE AS bf, exp(4::DOUBLE) AS f0, 1 - exp(4::DOUBLE) AS d0 FROM (VALUES {', '.join(f'({a}::DOUBLE)' for a in firsts)}) AS v(first))"
    for j in range(evaluations):
        text += f", x{j + 1} AS MATERIALIZED ({step.replace('x{0}', f'x{j}')})"
    return f"{text} SELECT first, round(best, 6) + 0.0 AS alpha, n_eval FROM x{evaluations}"
