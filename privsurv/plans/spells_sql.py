"""SQL of the workloads' spells and records, written for the oracle engine on its own."""

from __future__ import annotations

DAYS = "(epoch_us({b}) - epoch_us({a})) / 86400e6"

SPELLS = {
    "s1": f"""SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, strftime(l_shipdate, '%Y%m%d')) AS subject_id, o_custkey AS unit_id,
        {DAYS.format(a='o_orderdate', b='l_shipdate')} AS duration, (l_returnflag = 'R')::INT AS event,
        l_quantity::DOUBLE AS x1, l_extendedprice::DOUBLE AS x2, l_discount::DOUBLE AS x3, l_tax::DOUBLE AS x4, (l_linestatus = 'F')::INT::DOUBLE AS x5,
        p_size::DOUBLE AS x6, p_retailprice::DOUBLE AS x7, o_totalprice::DOUBLE AS x8
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE l_shipdate > o_orderdate""",
    "s4": f"""SELECT event_id AS subject_id, user_id AS unit_id,
        CASE WHEN wait <= 6 THEN wait ELSE least(6.0, {DAYS.format(a='ts', b='data_end')}) END AS duration, coalesce(wait <= 6, false)::INT AS event,
        value::DOUBLE AS x1, json_extract_string(props, '$.k')::DOUBLE AS x2, hour(ts)::DOUBLE AS x3
        FROM (SELECT *, {DAYS.format(a='ts', b='bought')} AS wait FROM (
            SELECT *, min(CASE WHEN event_type = 'purchase' THEN ts END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS bought
            FROM events WHERE event_type IN ('signup', 'purchase')), (SELECT max(ts) AS data_end FROM events)) WHERE event_type = 'signup'""",
    "s5": """SELECT conv_id AS subject_id, conv_id AS unit_id, count(*)::DOUBLE AS duration, (arg_max(role, turn) = 'assistant')::INT AS event,
        (arg_min(role, turn) = 'system')::INT::DOUBLE AS x1, avg(length(text)) AS x2, count(DISTINCT role)::DOUBLE AS x3 FROM conversations GROUP BY conv_id""",
    "s6": """SELECT doc_id AS subject_id, doc_id AS unit_id, n_chars::DOUBLE AS duration, toxic::INT AS event, quality::DOUBLE AS x1,
        (lang = 'de')::INT::DOUBLE AS x2, (lang = 'es')::INT::DOUBLE AS x3, (lang = 'fr')::INT::DOUBLE AS x4 FROM labels JOIN documents USING (doc_id)""",
}


def _orders(k: int) -> str:
    middle = "(c_mktsegment = 'BUILDING')::INT::DOUBLE" if k == 1 else DAYS.format(a=f"date{k - 1}", b=f"date{k}")
    wide = ", ".join(f"max(CASE WHEN k = {i} THEN o_orderdate END) AS date{i}, max(CASE WHEN k = {i} THEN o_totalprice END) AS price{i}" for i in range(1, k + 2))
    return f"""SELECT o_custkey AS subject_id, o_custkey AS unit_id, {DAYS.format(a=f'date{k}', b=f"coalesce(date{k + 1}, TIMESTAMP '1995-07-01')")} AS duration,
        (date{k + 1} IS NOT NULL)::INT AS event, c_acctbal::DOUBLE AS x1, {middle} AS x2, price{k}::DOUBLE AS x3
        FROM (SELECT o_custkey, {wide} FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS k FROM orders
            WHERE o_orderdate < TIMESTAMP '1995-07-01') GROUP BY 1) JOIN customer ON o_custkey = c_custkey WHERE date{k} IS NOT NULL"""


SPELLS |= {"s2": _orders(1), "s3": _orders(2)}
SIZE = {"s1": (200, 2500, 8), "s2": (200, 181, 3), "s3": (200, 181, 3), "s4": (200, 6, 3), "s5": (8, 8, 3), "s6": (50, 50_000, 4), "s7": (9, 9, 64)}
SPELLS["s7"] = f"""SELECT vec_id AS subject_id, vec_id AS unit_id, least(label + 1, 9)::DOUBLE AS duration, (label < 9)::INT AS event,
    {', '.join(f'embedding[{i}]::DOUBLE AS x{i}' for i in range(1, 65))} FROM embeddings"""


def records(name: str, tables: str = "records") -> str:
    """Common table expressions that end in ``records``: t, y and covariates centred and fitted into the ball."""
    q, horizon, p = SIZE[name]
    cut = f"greatest(1, least({q}, ceil(duration / {float(horizon)} * {q})))::INT AS t, 2 * event - 1 AS y"
    if name == "s7":
        return f"raw AS ({SPELLS[name]}), {tables} AS (SELECT *, {cut}, 1 AS w FROM raw)"
    x = [f"x{i + 1}" for i in range(p)]
    norm = "sqrt(" + " + ".join(f"{c} * {c}" for c in x) + ")"
    return f"""raw AS ({SPELLS[name]}), timed AS (SELECT *, {cut} FROM raw),
    centred AS (SELECT subject_id, unit_id, event, t, y, {', '.join(f'{c} - avg({c}) OVER () AS {c}' for c in x)} FROM timed),
    sized AS (SELECT *, max({norm}) OVER () AS r FROM centred),
    {tables} AS (SELECT subject_id, unit_id, event, t, y, {', '.join(f'{c} / CASE WHEN r > 0 THEN r ELSE 1.0 END AS {c}' for c in x)}, 1 AS w FROM sized)"""


def spline(e: int, u: str = "u") -> list[str]:
    """Basis functions at u."""
    k = [j / (e - 1) for j in range(e)]
    cube = lambda c: f"power(greatest({u} - {c}, 0), 3)"
    part = lambda j: f"(({cube(k[j])} - {cube(k[-1])}) / {k[-1] - k[j]})"
    return ["1.0", u, *[f"({part(j)} - {part(e - 2)})" for j in range(e - 2)]]


def basis(q: int, e: int = 3, name: str = "basis", grid: float = 0.0) -> str:
    cols = ", ".join(f"{c} AS a{i + 1}" for i, c in enumerate(spline(e)))
    return f"{name} AS (SELECT s, {cols} FROM (SELECT s, (s - {grid}) / {float(q)} AS u FROM range(1, {q + 1}) r(s)))"


def softplus(u: str) -> str:
    return f"(greatest({u}, 0) + ln(1 + exp(-abs({u}))))"


def periods(alpha: list[float], beta: list[float], name: str = "periods", source: str = "records") -> str:
    """Person-period rows with their score eta and whether they fail."""
    gamma = " + ".join(f"{a} * a{i + 1}" for i, a in enumerate(alpha))
    z = " + ".join(f"{b} * x{i + 1}" for i, b in enumerate(beta)) or "0"
    return f"{name} AS (SELECT r.*, s, a1, a2, a3, ({gamma}) + ({z}) AS eta, (s = t AND y = 1)::INT AS fails FROM {source} r JOIN basis ON s <= t)"
