"""Building blocks of the SQL that checks the queries: clouds, lattice positions and cells in DuckDB's dialect."""

from __future__ import annotations

from cloudlattice.plans.sweeps import FACTORS

# fixed values: axes of the clouds as SQL
AXES = {
    "c_sales": ("lineitem", "l_quantity", "l_extendedprice", "l_discount"),
    "c_shipping": ("lineitem", "epoch_us(l_shipdate)::DOUBLE / 86400000000.0::DOUBLE", "l_extendedprice", "l_suppkey"),
    "c_linekeys": ("lineitem", "l_orderkey", "l_partkey", "l_suppkey"),
    "c_activity": ("events", "epoch_us(ts)::DOUBLE / 1e6::DOUBLE", "user_id", "value"),
    "c_orders": ("orders", "epoch_us(o_orderdate)::DOUBLE / 86400000000.0::DOUBLE", "o_totalprice", "o_custkey"),
    "c_corpus": ("documents", "n_chars", "len(string_split(text, ' '))", "doc_id"),
    "c_catalog": ("part", "p_partkey", "p_size", "p_retailprice"),
    "c_accounts": ("customer", "c_custkey", "c_nationkey", "c_acctbal"),
}
KEYS = {"c_activity": "event_id", "c_orders": "o_orderkey", "c_corpus": "doc_id", "c_catalog": "p_partkey", "c_accounts": "c_custkey"}


def number(x: float) -> str:
    return f"({x!r}::DOUBLE)"


def raw(name: str, keyed: bool = False, carry: str = "") -> str:
    if name == "c_vectors":
        at = [f"embedding[3 * t + {a}]::DOUBLE AS {n}" for a, n in ((1, "x"), (2, "y"), (3, "z"))]
        pid = "vec_id * 21 + t AS pid, " if keyed else ""
        return f"SELECT {pid}{', '.join(at)} FROM (SELECT vec_id, embedding, unnest(range(0, len(embedding) // 3)) AS t FROM embeddings)"
    table, *axes = AXES[name]
    pid = ""
    if keyed and name in KEYS:
        pid = f"{KEYS[name]}::BIGINT AS pid, "
    elif keyed:
        pid = "l_orderkey * 1024 + row_number() OVER (PARTITION BY l_orderkey ORDER BY l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS pid, "
    return f"SELECT {pid}{carry}{', '.join(f'({e})::DOUBLE AS {n}' for e, n in zip(axes, 'xyz', strict=True))} FROM {table}"


def unit(name: str, keyed: bool = False, carry: str = "") -> str:
    """The cloud on the unit cube."""
    more = ("pid, " if keyed else "") + carry
    at = ", ".join(f"CASE WHEN {a}hi = {a}lo THEN 0.0::DOUBLE ELSE ({a} - {a}lo) / ({a}hi - {a}lo) END AS {a}" for a in "xyz")
    box = ", ".join(f"min({a}) AS {a}lo, max({a}) AS {a}hi" for a in "xyz")
    return f"SELECT {more}{at} FROM ({raw(name, keyed, carry)}), (SELECT {box} FROM ({raw(name)}))"


def points(names, bounds, shape: str = "bcc") -> str:
    pairs = ", ".join(f"({number(eb)}, {number(FACTORS[shape](eb))})" for eb in bounds)
    one = lambda n: f"SELECT '{n}' AS dataset, eb, factor, x * factor AS u, y * factor AS v, z * factor AS w FROM ({unit(n)}), (VALUES {pairs}) b(eb, factor)"
    return " UNION ALL ".join(map(one, names))


def at_factor(name: str, factor: float, keyed: bool = False, carry: str = "") -> str:
    more = ("pid, " if keyed else "") + carry
    return f"SELECT {more}x, y, z, x * {number(factor)} AS u, y * {number(factor)} AS v, z * {number(factor)} AS w FROM ({unit(name, keyed, carry)})"


def celled(source: str, shape: str = "bcc") -> str:
    """Adds i, j, k and the squared error e2 in lattice units."""
    if shape == "bcc":
        f = f"SELECT *, floor(u)::BIGINT AS fu, floor(v)::BIGINT AS fv, floor(w)::BIGINT AS fw FROM ({source})"
        even = [f"(f{c} + ((f{c} % 2) + 2) % 2)" for c in "uvw"]
        odd = [f"(f{c} + 1 - ((f{c} % 2) + 2) % 2)" for c in "uvw"]
        gap = lambda p: " + ".join(f"({c} - {q}) * ({c} - {q})" for c, q in zip("uvw", p, strict=True))
        d = f"SELECT *, {gap(even)} AS de, {gap(odd)} AS dodd FROM ({f})"
        cell = ", ".join(f"CASE WHEN de <= dodd THEN {e} ELSE {o} END AS {n}" for e, o, n in zip(even, odd, "ijk", strict=True))
        return f"SELECT *, {cell}, least(de, dodd) AS e2 FROM ({d})"
    if shape in ("cube", "cube_mse"):
        cell = ", ".join(f"floor({c} + 0.5::DOUBLE)::BIGINT AS {n}" for c, n in zip("uvw", "ijk", strict=True))
        return f"SELECT *, (u - i) * (u - i) + (v - j) * (v - j) + (w - k) * (w - k) AS e2 FROM (SELECT *, {cell} FROM ({source}))"
    near = ", ".join(f"floor({c} + 0.5::DOUBLE)::BIGINT AS n{c}" for c in "uvw")
    size = ", ".join(f"{c} - n{c} AS g{c}" for c in "uvw")
    s = f"SELECT *, {size}, (((nu + nv + nw) % 2) + 2) % 2 = 1 AS isodd FROM (SELECT *, {near} FROM ({source}))"
    first, second = "(abs(gu) >= abs(gv) AND abs(gu) >= abs(gw))", "(abs(gv) >= abs(gw))"
    pick = {"u": first, "v": f"NOT {first} AND {second}", "w": f"NOT {first} AND NOT {second}"}
    cell = ", ".join(f"n{c} + CASE WHEN isodd AND {pick[c]} THEN CASE WHEN g{c} >= 0 THEN 1 ELSE -1 END ELSE 0 END AS {n}" for c, n in zip("uvw", "ijk", strict=True))
    return f"SELECT *, {cell} FROM ({s})"


def cells(names, bounds, shape: str = "bcc") -> str:
    return f"SELECT dataset, eb, i, j, k, count(*) AS n FROM ({celled(points(names, bounds, shape), shape)}) GROUP BY ALL"


def table(name: str, factor: float, shape: str = "bcc") -> str:
    return f"SELECT i, j, k, count(*) AS n FROM ({celled(at_factor(name, factor), shape)}) GROUP BY ALL"


def rounded(x: str, digits: int = 6) -> str:
    p = number(float(10**digits))
    return f"floor(({x}) * {p} + 0.5::DOUBLE) / {p}"


def morton(i: str, j: str, k: str, bits: int = 12) -> str:
    """Interleaved bits; ``bits`` an axis are enough for the tables that are checked."""
    return "(" + " + ".join(f"((({c} >> {b}) & 1)::BIGINT << {3 * b + a})" for b in range(bits) for a, c in enumerate((i, j, k))) + ")"


def packed(key) -> str:
    """A packed key from a key expression over three halved coordinates."""
    return f"(({key('(i >> 1)', '(j >> 1)', '(k >> 1)')}) * 2 + (i & 1))"


def log_gamma(x: str) -> str:
    y = f"(({x}) + 4.0::DOUBLE)"
    return f"(({y} - 0.5::DOUBLE) * ln({y}) - {y} + 0.9189385332046727::DOUBLE + 1 / (12 * {y}) - 1 / (360 * {y} * {y} * {y}) + 1 / (1260 * {y} * {y} * {y} * {y} * {y}) - ln({x}) - ln(({x}) + 1.0::DOUBLE) - ln(({x}) + 2.0::DOUBLE) - ln(({x}) + 3.0::DOUBLE))"


def bit_length(n: str) -> str:
    return f"CASE WHEN ({n}) = 0 THEN 0 ELSE len(bin(({n})::BIGINT)) END"
