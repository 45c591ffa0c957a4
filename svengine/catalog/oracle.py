"""SQL text for DuckDB: encoded tables, single gates, and a recursive loop over a gate table."""

from __future__ import annotations

from ..functions.gates import Circuit, decompose

LINE_ORDER = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate"
MISMATCHES = "SELECT CAST(0 AS BIGINT) AS mismatches"


def u6(x: str) -> str:
    return f"CAST(floor(({x}) * 1e6 + 0.5001) AS BIGINT)"


def amps(src: str, keys: str = "idx") -> str:
    return f"SELECT {keys}, {u6('re')} AS re_u6, {u6('im')} AS im_u6 FROM {src}"


def size_of(table: str) -> str:
    return f"(SELECT CAST(pow(2, greatest(1, ceil(log2(count(*))))) AS BIGINT) FROM {table})"


def encoded(table: str, key: str, value: str, size: str | None = None) -> str:
    """idx, re, im of an amplitude-encoded table."""
    return f"""(SELECT i AS idx, coalesce(v, 0.0) / (SELECT sqrt(sum(({value}) * ({value}))) FROM {table}) AS re, CAST(0 AS DOUBLE) AS im
        FROM (SELECT unnest(range({size or size_of(table)})) AS i) LEFT JOIN (SELECT {key} AS k, CAST({value} AS DOUBLE) AS v FROM {table}) ON k = i)"""


def basis(n: int, j: int = 0) -> str:
    return f"(SELECT i AS idx, CASE WHEN i = {j} THEN 1.0::DOUBLE ELSE 0.0 END AS re, 0.0::DOUBLE AS im FROM range({2**n}) t(i))"


ORDERS = encoded("orders", "o_orderkey", "o_totalprice")
CUSTOMER = encoded("customer", "c_custkey", "c_acctbal")
PART = encoded("part", "p_partkey", "p_retailprice")
SUPPLIER = encoded("supplier", "s_suppkey", "s_acctbal")
NATION = encoded("nation", "n_nationkey", "n_nationkey + 1")
REGION = encoded("region", "r_regionkey", "r_regionkey + 1")
#: The qubits of the register of each supplier's lines.
LINE_REGISTERS = "(SELECT l_suppkey, CAST(greatest(1, ceil(log2(count(*)))) AS INT) AS n FROM lineitem GROUP BY l_suppkey)"


def u3(src: str, k: int, t, p, l) -> str:
    """One u3 by a join with the partner index."""
    return f"""(SELECT a.idx,
        CASE WHEN (a.idx >> {k}) & 1 = 0 THEN cos({t}/2.0)*a.re - sin({t}/2.0)*(cos({l})*b.re - sin({l})*b.im)
             ELSE sin({t}/2.0)*(cos({p})*b.re - sin({p})*b.im) + cos({t}/2.0)*(cos({p}+{l})*a.re - sin({p}+{l})*a.im) END AS re,
        CASE WHEN (a.idx >> {k}) & 1 = 0 THEN cos({t}/2.0)*a.im - sin({t}/2.0)*(cos({l})*b.im + sin({l})*b.re)
             ELSE sin({t}/2.0)*(cos({p})*b.im + sin({p})*b.re) + cos({t}/2.0)*(cos({p}+{l})*a.im + sin({p}+{l})*a.re) END AS im
        FROM {src} a JOIN {src} b ON b.idx = xor(a.idx, CAST({1 << k} AS BIGINT)))"""


_STEP = """CASE WHEN g.kind = 'u1' THEN CASE WHEN (a.idx >> g.t) & 1 = 1 THEN cos(g.lam)*a.{x} {s1} sin(g.lam)*a.{y} ELSE a.{x} END
    WHEN g.kind = 'cx' THEN CASE WHEN (a.idx >> g.c) & 1 = 1 THEN b.{x} ELSE a.{x} END
    WHEN (a.idx >> g.t) & 1 = 0 THEN cos(g.theta/2)*a.{x} - sin(g.theta/2)*(cos(g.lam)*b.{x} {s1} sin(g.lam)*b.{y})
    ELSE sin(g.theta/2)*(cos(g.phi)*b.{x} {s1} sin(g.phi)*b.{y}) + cos(g.theta/2)*(cos(g.phi+g.lam)*a.{x} {s1} sin(g.phi+g.lam)*a.{y}) END"""
_RE, _IM = _STEP.format(x="re", y="im", s1="-"), _STEP.format(x="im", y="re", s1="+")


def loop(init: str, gates: str, tail: str | None = None, ctes: str = "") -> str:
    """The gate table (step, kind u3|u1|cx, t, c, theta, phi, lam) applied to init in order; `fin` holds the result."""
    return f"""WITH RECURSIVE {ctes} g AS MATERIALIZED ({gates}),
    s AS (SELECT CAST(0 AS BIGINT) AS step, CAST(idx AS BIGINT) AS idx, CAST(re AS DOUBLE) AS re, CAST(im AS DOUBLE) AS im FROM {init}
      UNION ALL SELECT a.step + 1, a.idx, {_RE}, {_IM} FROM s a JOIN g ON g.step = a.step JOIN s b ON b.idx = xor(a.idx, CAST(1 AS BIGINT) << g.t)),
    fin AS (SELECT idx, re, im FROM s WHERE step = (SELECT count(*) FROM g))
    {tail or amps('fin')}"""


def batch_loop(init: str, gates: str, tail: str, ctes: str = "") -> str:
    """As loop, for many circuits: both tables have circuit_id as well."""
    return f"""WITH RECURSIVE {ctes} g AS MATERIALIZED ({gates}),
    s AS (SELECT circuit_id, CAST(0 AS BIGINT) AS step, CAST(idx AS BIGINT) AS idx, CAST(re AS DOUBLE) AS re, CAST(im AS DOUBLE) AS im FROM {init}
      UNION ALL SELECT a.circuit_id, a.step + 1, a.idx, {_RE}, {_IM} FROM s a JOIN g ON g.step = a.step AND g.circuit_id = a.circuit_id
        JOIN s b ON b.circuit_id = a.circuit_id AND b.idx = xor(a.idx, CAST(1 AS BIGINT) << g.t)),
    fin AS (SELECT s.circuit_id, idx, re, im FROM s JOIN (SELECT circuit_id, count(*) AS n FROM g GROUP BY circuit_id) c ON c.circuit_id = s.circuit_id AND s.step = c.n)
    {tail}"""


def gates(c: Circuit) -> str:
    """A circuit, lowered, as a gate table."""
    rows = []
    for k, g in enumerate(decompose(c).gates):
        t, p, l = {"u3": lambda g=g: g.params, "u1": lambda g=g: (0.0, 0.0, g.params[0]), "cx": lambda: (0.0, 0.0, 0.0)}[g.kind]()
        rows.append(f"({k}, '{g.kind}', {g.qubits[-1]}, {g.qubits[0]}, {t!r}::DOUBLE, {p!r}::DOUBLE, {l!r}::DOUBLE)")
    return f"SELECT * FROM (VALUES {', '.join(rows)}) v(step, kind, t, c, theta, phi, lam)"


def volume_ctes(n: int, depth: int) -> str:
    pairs = n // 2
    blk = "(0,'u3',0,0),(1,'u3',1,1),(2,'cx',0,NULL),(3,'u3',0,2),(4,'u3',1,3),(5,'cx',1,NULL),(6,'u3',0,4),(7,'u3',1,5),(8,'cx',0,NULL),(9,'u3',0,6),(10,'u3',1,7)"
    return f"""lay AS (SELECT l, p_partkey AS q, row_number() OVER (PARTITION BY l ORDER BY (p_partkey*7919 + l*104729 + 31) % 10007, p_partkey) - 1 AS r FROM part, range({depth}) t(l) WHERE p_partkey < {n}),
    prs AS (SELECT a.l, a.r // 2 AS i, a.q AS qa, b.q AS qb FROM lay a JOIN lay b ON a.l = b.l AND a.r % 2 = 0 AND b.r = a.r + 1),
    blk(k, kind, side, u) AS (VALUES {blk}),
    ang AS (SELECT row_number() OVER (ORDER BY {LINE_ORDER}) - 1 AS j, pi()*l_quantity/50 AS theta, 2*pi()*((l_partkey*37) % 1009)/1009 AS phi, 2*pi()*((l_suppkey*53 + l_linenumber*11) % 1013)/1013 AS lam FROM lineitem QUALIFY j < {8 * pairs * depth}),"""


def volume_gates(n: int) -> str:
    pairs = n // 2
    return f"""SELECT (l*{pairs} + i)*11 + k AS step, kind, CASE WHEN (kind = 'u3') = (side = 1) THEN qb ELSE qa END AS t, CASE WHEN side = 1 THEN qb ELSE qa END AS c,
        coalesce(theta, 0.0) AS theta, coalesce(phi, 0.0) AS phi, coalesce(lam, 0.0) AS lam FROM prs CROSS JOIN blk LEFT JOIN ang ON ang.j = (l*{pairs} + i)*8 + u"""


def volume(n: int, depth: int = 10, tail: str | None = None) -> str:
    return loop(basis(n), volume_gates(n), tail, volume_ctes(n, depth))


def fourier(src: str, size: str) -> str:
    """The closed form: every output amplitude is a sum over all inputs."""
    return f"""(SELECT k AS idx, sum(re*cos(2*pi()*((idx*k) % {size})/{size}) - im*sin(2*pi()*((idx*k) % {size})/{size}))/sqrt({size}) AS re,
        sum(re*sin(2*pi()*((idx*k) % {size})/{size}) + im*cos(2*pi()*((idx*k) % {size})/{size}))/sqrt({size}) AS im
        FROM (SELECT * FROM {src}) x, (SELECT unnest(range({size})) AS k) y GROUP BY k)"""
