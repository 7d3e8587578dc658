"""SQL that checks the factorizations: Gram sums, Cholesky by columns and Q by substitution, as chains of common table expressions."""

from __future__ import annotations

LINE = "l_orderkey AS k0, l_linenumber AS k1, l_partkey AS k2, l_suppkey AS k3, l_quantity AS k4, l_extendedprice AS k5"
KEYS = ", ".join(f"k{i}" for i in range(6))
RAW4 = f"SELECT {LINE}, l_quantity AS a0, l_extendedprice AS a1, l_discount AS a2, l_tax AS a3 FROM lineitem"
PART2 = "SELECT p_partkey AS k0, p_size::DOUBLE AS a0, p_retailprice AS a1 FROM part"
ORD5 = "SELECT o_orderkey AS k0, 1.0::DOUBLE AS a0, o_totalprice AS a1, c_acctbal AS a2, month(o_orderdate)::DOUBLE AS a3, isodow(o_orderdate)::DOUBLE AS a4 FROM orders JOIN customer ON o_custkey = c_custkey"
PAGE5 = "SELECT page_id AS k0, " + ", ".join(f"((length(html) - length(replace(html, '{s}', ''))) / {len(s)})::DOUBLE AS a{i}" for i, s in enumerate(("<p", "<a", "<li", "&amp;"))) + ", length(html)::DOUBLE AS a4 FROM pages"
TURN4 = "SELECT conv_id AS k0, 1.0::DOUBLE AS a0, turn::DOUBLE AS a1, length(coalesce(text, ''))::DOUBLE AS a2, (coalesce(role, '') = 'user')::DOUBLE AS a3 FROM conversations"

EVENT10 = (
    "WITH s AS (SELECT event_id AS k0, greatest(-1.0, least(1.0, value / 300 - 1)) AS x, hour(ts) / 11.5 - 1 AS y FROM events), t AS (SELECT *, 2 * y * y - 1 AS y2 FROM s), u AS (SELECT *, 2 * y * y2 - y AS y3 FROM t), v AS (SELECT *, 2 * y * y3 - y2 AS y4 FROM u) SELECT k0, "
    + ", ".join(f"({a} * {b})::DOUBLE AS a{5 * i + j}" for i, a in enumerate(("1.0", "x")) for j, b in enumerate(("1.0", "y", "y2", "y3", "y4")))
    + " FROM v"
)


def cheb(a: int, b: int) -> str:
    """Products of polynomials, i-major, by the recurrence over columns."""
    steps = [f"s AS (SELECT {LINE}, (l_quantity - 25.5) / 24.5 AS x, greatest(-1.0, least(1.0, (l_extendedprice - 52950.0) / 52050.0)) AS y FROM lineitem)"]
    last = "s"
    for v, degree in (("x", a), ("y", b)):
        steps.append(f"{v}_1 AS (SELECT *, 1.0::DOUBLE AS {v}0, {v} AS {v}1 FROM {last})")
        last = f"{v}_1"
        for i in range(2, degree):
            steps.append(f"{v}_{i} AS (SELECT *, 2 * {v} * {v}{i - 1} - {v}{i - 2} AS {v}{i} FROM {last})")
            last = f"{v}_{i}"
    columns = ", ".join(f"x{i} * y{j} AS a{i * b + j}" for i in range(a) for j in range(b))
    return f"(WITH {', '.join(steps)} SELECT {KEYS}, {columns} FROM {last})"


def gram_sums(n: int) -> str:
    return ", ".join(f"sum(a{i} * a{j}) AS g{i}_{j}" for i in range(n) for j in range(i, n))


def gram_sql(source: str, n: int, digits: int, upper: bool = False) -> str:
    cells = " UNION ALL ".join(f"SELECT {i} AS i, {j} AS j, round(g{min(i, j)}_{max(i, j)}, {digits}) + 0.0 AS v FROM g" for i in range(n) for j in range(i if upper else 0, n))
    return f"WITH a AS ({source}), g AS (SELECT {gram_sums(n)} FROM a) {cells}"


def cholesky_chain(n: int, start: str = "g", by: str = "") -> tuple[str, str]:
    """CTEs that add a column of R each, and the name of the last."""
    out, last = [], start
    for j in range(n):
        lower = lambda i, j=j: "".join(f" - r{k}_{j} * r{k}_{i}" for k in range(j))
        out.append(f"d{j} AS (SELECT *, sqrt(g{j}_{j}{lower(j)}) AS r{j}_{j} FROM {last})")
        out.append(f"c{j} AS (SELECT *{''.join(f', (g{j}_{i}{lower(i)}) / r{j}_{j} AS r{j}_{i}' for i in range(j + 1, n))} FROM d{j})")
        last = f"c{j}"
    return ", ".join(out), last


def r_sql(source: str, n: int, digits: int, by: str = "") -> str:
    """(group, i, j, v) of R, upper triangle."""
    chain, last = cholesky_chain(n)
    head = f"{by}, " if by else ""
    cells = " UNION ALL ".join(f"SELECT {head}{i} AS i, {j} AS j, round(r{i}_{j}, {digits}) + 0.0 AS v FROM {last}" for i in range(n) for j in range(i, n))
    return f"WITH a AS ({source}), g AS (SELECT {head}{gram_sums(n)} FROM a {f'GROUP BY {by}' if by else ''}), {chain} {cells}"


def q_sql(source: str, n: int, digits: int, keys: str = KEYS) -> str:
    """(keys, q0, ...) by substitution with R."""
    chain, last = cholesky_chain(n)
    rows = f"b AS (SELECT a.*, {', '.join(f'r{i}_{j}' for i in range(n) for j in range(i, n))} FROM a, {last})"
    steps, now = [], "b"
    for j in range(n):
        known = "".join(f" - q{i} * r{i}_{j}" for i in range(j))
        steps.append(f"s{j} AS (SELECT *, (a{j}{known}) / r{j}_{j} AS q{j} FROM {now})")
        now = f"s{j}"
    return f"WITH a AS ({source}), g AS (SELECT {gram_sums(n)} FROM a), {chain}, {rows}, {', '.join(steps)} SELECT {keys}, {', '.join(f'round(q{j}, {digits}) + 0.0 AS q{j}' for j in range(n))} FROM {now}"


def sigma2_sql(source: str, digits: int) -> str:
    """Singular values of two columns, from trace and determinant."""
    return f"""WITH a AS ({source}), g AS (SELECT sum(a0 * a0) AS p, sum(a0 * a1) AS q, sum(a1 * a1) AS r FROM a),
        e AS (SELECT (p + r) / 2 AS t, sqrt((p - r) * (p - r) / 4 + q * q) AS d, p * r - q * q AS det FROM g)
        SELECT 0 AS k, round(sqrt(t + d), {digits}) AS sigma FROM e UNION ALL SELECT 1, round(sqrt(det / (t + d)), {digits}) FROM e"""
