"""DuckDB texts for the queries, by other routes than the engine's: per-marker SQL, lgamma, erfc by series and
continued fraction, window ranks, joins instead of bitsets."""

from __future__ import annotations


def panel(name: str, prefix: str = "") -> str:
    """CTEs <prefix>cells(marker, ind, depth) and <prefix>groups(ind, grp)."""
    words = "unnest(list_filter(string_split(lower({}), ' '), lambda w: w <> ''))"
    letters = "translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC')"
    source = "1 + CAST(substr(ind, 4) AS INT) % 2"
    count = "SELECT marker, ind, CAST(count(*) AS INT) AS depth FROM ({}) GROUP BY ALL"
    planted = "SELECT l_partkey // {0} AS marker, l_orderkey % {2} AS ind FROM lineitem WHERE NOT ((l_partkey // {0} % {1} = 3 AND l_orderkey % 2 = 1{3}) OR (l_partkey // {0} % {1} = 7 AND l_orderkey % 2 = 0))"
    rows, groups = {
        "P1": ("SELECT l_partkey AS marker, c_nationkey AS ind FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey", "SELECT n_nationkey AS ind, CASE WHEN n_regionkey <= 1 THEN 1 WHEN n_regionkey >= 3 THEN 2 END AS grp FROM nation"),
        "P2": (planted.format(5, 25, 40, ""), "SELECT range AS ind, 1 + range % 2 AS grp FROM range(40)"),
        "P3": (planted.format(2, 50, 20, " AND l_linenumber <> 1"), "SELECT range AS ind, 1 + range % 2 AS grp FROM range(20)"),
        "P4": (f"SELECT {words.format('text')} AS marker, doc_id AS ind FROM documents JOIN labels USING (doc_id)", "SELECT doc_id AS ind, CASE WHEN quality = 1 THEN 1 ELSE 2 END AS grp FROM documents JOIN labels USING (doc_id)"),
        "P5": (f"SELECT {words.format('text')} AS marker, doc_id AS ind FROM documents WHERE doc_id IN (SELECT doc_id FROM (SELECT doc_id, row_number() OVER (PARTITION BY lang ORDER BY doc_id) AS r FROM documents WHERE lang IN ('en', 'fr')) WHERE r <= 30)", "SELECT doc_id AS ind, CASE WHEN lang = 'en' THEN 1 ELSE 2 END AS grp FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY doc_id) AS r FROM documents WHERE lang IN ('en', 'fr')) WHERE r <= 30"),
        "P6": (f"SELECT {words.format('text')} AS marker, source AS ind FROM documents", f"SELECT DISTINCT ind, {source} AS grp FROM (SELECT source AS ind FROM documents)"),
        "P7": (f"SELECT {words.format('text')} AS marker, conv_id * 10 + turn AS ind FROM conversations WHERE role IN ('user', 'assistant')", "SELECT DISTINCT conv_id * 10 + turn AS ind, CASE WHEN role = 'user' THEN 1 ELSE 2 END AS grp FROM conversations WHERE role IN ('user', 'assistant')"),
        "P8": ("SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d %H') || '|' || event_type AS marker, user_id AS ind FROM events", "SELECT DISTINCT user_id AS ind, 1 + user_id % 2 AS grp FROM events"),
        "P9": (f"SELECT substr(s, CAST(i * 94 + 1 AS INT), 94) AS marker, source AS ind FROM (SELECT source, s, unnest(range(0, length(s) // 94)) AS i FROM (SELECT source, {letters} AS s FROM documents))", f"SELECT DISTINCT ind, {source} AS grp FROM (SELECT source AS ind FROM documents)"),
        "P11": ("SELECT l_partkey AS marker, l_suppkey AS ind FROM lineitem", "SELECT s_suppkey AS ind, 1 + s_nationkey % 2 AS grp FROM supplier"),
    }[name]
    return f"{prefix}cells AS ({count.format(rows)}), {prefix}groups AS ({groups})"


CONTIGS = "contigs AS (SELECT item_id AS contig, translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC') AS seq FROM benchmark)"


def counts(d: int = 1, prefix: str = "", keep: str = "g1 + g2 > 0") -> str:
    """CTEs <prefix>counts(marker, g1, g2, n_ind) and <prefix>sizes(n1, n2, n)."""
    p = prefix
    return f"""{p}sizes AS (SELECT count(*) FILTER (WHERE grp = 1) AS n1, count(*) FILTER (WHERE grp = 2) AS n2, count(*) FILTER (WHERE grp IS NOT NULL) AS n FROM {p}groups),
{p}counts AS (SELECT * FROM (SELECT marker, count(*) FILTER (WHERE grp = 1) AS g1, count(*) FILTER (WHERE grp = 2) AS g2, count(*) AS n_ind FROM {p}cells LEFT JOIN {p}groups USING (ind) WHERE depth >= {d} GROUP BY marker) WHERE {keep})"""


def chi2(correct: bool = True) -> str:
    gap = f"greatest(abs(g1 * (n2 - g2) - g2 * (n1 - g1)) - {'n / 2.0' if correct else '0'}, 0)"
    return f"CASE WHEN g1 + g2 = 0 OR g1 + g2 = n OR n1 * n2 = 0 THEN 0.0 ELSE pow({gap}, 2) * n / (CAST(n1 * n2 AS DOUBLE) * (g1 + g2) * (n - g1 - g2)) END"


def g_stat() -> str:
    cell = lambda o, row, col: f"(CASE WHEN {o} > 0 AND {row} > 0 THEN ({o}) * ln(CAST({o} AS DOUBLE) * n / (({row}) * {col})) ELSE 0.0 END)"
    return f"greatest(2 * ({cell('g1', 'g1 + g2', 'n1')} + {cell('g2', 'g1 + g2', 'n2')} + {cell('(n1 - g1)', 'n - g1 - g2', 'n1')} + {cell('(n2 - g2)', 'n - g1 - g2', 'n2')}), 0.0)"


def erfc(t: str = "t") -> str:
    """Series below 2, continued fraction above, written out."""
    series = "1.0"
    for k in range(45, 0, -1):
        series = f"1.0 + 2.0 * {t} * {t} / {2 * k + 1} * ({series})"
    tail = t
    for k in range(60, 0, -1):
        tail = f"{t} + {k / 2} / ({tail})"
    return f"CASE WHEN {t} >= 6 THEN 0.0 WHEN {t} < 2 THEN 1 - 2 / sqrt(pi()) * exp(-{t} * {t}) * {t} * ({series}) ELSE exp(-{t} * {t}) / sqrt(pi()) / ({tail}) END"


LB = "(lgamma({0}) + lgamma({1}) - lgamma(({0}) + ({1})))"


def lbeta(a: str, b: str) -> str:
    return LB.format(a, b)


def log_bf(s=(1, 1, 1, 1, 1, 1)) -> str:
    a1, b1, a2, b2, a0, b0 = map(float, s)
    return f"({lbeta(f'g1 + {a1}', f'n1 - g1 + {b1}')} + {lbeta(f'g2 + {a2}', f'n2 - g2 + {b2}')} + {lbeta(str(a0), str(b0))} - {lbeta(str(a1), str(b1))} - {lbeta(str(a2), str(b2))} - {lbeta(f'g1 + g2 + {a0}', f'n - g1 - g2 + {b0}')})"


def evidence_of(k: str, family: tuple) -> str:
    """ln evidence of k among n: ('fixed', q) or ('beta', a, b)."""
    if family[0] == "fixed":
        return f"(({k}) * ln({family[1]}) + (n - ({k})) * ln(1 - {family[1]}))"
    a, b = map(float, family[1:])
    return f"({lbeta(f'{k} + {a}', f'n - ({k}) + {b}')} - {lbeta(str(a), str(b))})"


def log_odds(linked=("fixed", 0.9), null=("fixed", 0.5), w: float = 0.5, pi: str = "0.01") -> str:
    one, two = evidence_of("g1 + n2 - g2", linked), evidence_of("n1 - g1 + g2", linked)
    return f"(greatest({one} + ln({w}), {two} + ln({1 - w})) + ln(1 + exp(-abs({one} + ln({w}) - ({two} + ln({1 - w}))))) - {evidence_of('g1 + g2', null)} + ln({pi} / (1 - {pi})))"


def post(odds: str = "log_odds") -> str:
    return f"(1 / (1 + exp(-greatest(least({odds}, 20.0), -20.0))))"


def tests(prefix: str = "", stat: str | None = None) -> str:
    """CTE <prefix>tests: counts with sizes, stat, p and the number of markers m."""
    p = prefix
    return f"""{p}stat AS (SELECT *, {stat or chi2()} AS stat, count(*) OVER () AS m FROM {p}counts, {p}sizes),
{p}half AS (SELECT *, sqrt(stat / 2) AS t FROM {p}stat),
{p}tests AS (SELECT *, greatest({erfc()}, 1e-16) AS p FROM {p}half)"""


def fisher(prefix: str = "", keep: str = "lp <= seen + 1e-7") -> str:
    """CTE <prefix>tests with Fisher's p per marker (evaluated per distinct pair)."""
    p = prefix
    lp = lambda x: f"(lgamma(n1 + 1) + lgamma(n2 + 1) - lgamma(n + 1) + lgamma(k + 1) + lgamma(n - k + 1) - lgamma({x} + 1) - lgamma(n1 - {x} + 1) - lgamma(k - {x} + 1) - lgamma(n2 - k + {x} + 1))"
    return f"""{p}pairs AS (SELECT DISTINCT g1, g2, g1 + g2 AS k, n1, n2, n FROM {p}counts, {p}sizes),
{p}outs AS (SELECT *, unnest(range(greatest(0, k - n2), least(n1, k) + 1)) AS x FROM {p}pairs),
{p}lps AS (SELECT g1, g2, x, {lp('x')} AS lp, {lp('g1')} AS seen FROM {p}outs),
{p}fp AS (SELECT g1, g2, greatest(least(1.0, coalesce(sum(exp(lp)) FILTER (WHERE {keep}), 0.0)), 1e-16) AS p FROM {p}lps GROUP BY g1, g2),
{p}tests AS (SELECT c.*, s.n1, s.n2, s.n, CAST(NULL AS DOUBLE) AS stat, fp.p, count(*) OVER () AS m FROM {p}counts c JOIN {p}fp fp USING (g1, g2), {p}sizes s)"""


def step_up(prefix: str = "") -> str:
    """CTE <prefix>adj: tests with Benjamini-Hochberg p_adj, ranked over all markers."""
    p = prefix
    return f"""{p}ranked AS (SELECT *, count(*) OVER (ORDER BY p RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS r FROM {p}tests),
{p}adj AS (SELECT *, least(1.0, min(p * m / r) OVER (ORDER BY p DESC RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)) AS p_adj FROM {p}ranked)"""


def graded(prefix: str = "", alpha: float = 0.05, tau_post: float = 0.9, tau_bf: float = 10.0, denominator: str = "m") -> str:
    """CTE <prefix>graded: tests with strict, log_bf, log_odds, posterior, class, direction."""
    p = prefix
    return f"""{p}ev AS (SELECT *, p < {alpha} / {denominator} AS strict, {log_bf()} AS log_bf, {log_odds()} AS log_odds FROM {p}tests),
{p}po AS (SELECT *, {post()} AS posterior FROM {p}ev),
{p}cl AS (SELECT *, CASE WHEN strict THEN 'strict' WHEN posterior > {tau_post} THEN 'posterior' WHEN log_bf > ln({tau_bf}) THEN 'weak' ELSE 'none' END AS class FROM {p}po),
{p}graded AS (SELECT *, CASE WHEN class = 'none' OR g1 * n2 = g2 * n1 THEN 'unsupported' WHEN g1 * n2 > g2 * n1 THEN 'xy' ELSE 'zw' END AS direction FROM {p}cl)"""


def i(expr: str, name: str | None = None) -> str:
    return f"CAST({expr} AS BIGINT) AS {name or expr}"


def r(expr: str, name: str | None = None, digits: int = 6) -> str:
    return f"round(CAST({expr} AS DOUBLE), {digits}) + 0.0 AS {name or expr}"


def nl(expr: str, name: str) -> str:
    return r(f"-log10({expr})", name)
