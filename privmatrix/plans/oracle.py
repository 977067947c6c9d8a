"""DuckDB texts for the registered queries, written from the definitions of the methods and not from the Spark plans."""

from __future__ import annotations

import hashlib
import math

SALT = "42"
TWO52 = "4503599627370496.0"


def key(method: str, eps: float, name: str, *details: object) -> str:
    """The salt of a release: a SHA-256 of the secret one and of all that sets the release apart."""
    shape = f"{name}:{'x'.join(map(str, WIDTHS[name]))}"
    return hashlib.sha256("|".join(map(str, (SALT, method, eps, shape, *details))).encode()).hexdigest()


def total_key(salt: str, eps0: float) -> str:
    return hashlib.sha256(f"{salt}|total|{eps0!r}||1.0".encode()).hexdigest()


def uniform(purpose: str, *keys: str, salt: str = SALT) -> str:
    parts = ", ".join(["'" + salt + "'", f"'{purpose}'", *[f"cast({k} AS VARCHAR)" for k in keys]])
    return f"((cast('0x' || substr(sha256(concat_ws('|', {parts})), 1, 13) AS BIGINT) + 0.5) / {TWO52})"


def laplace(purpose: str, scale: str, *keys: str, salt: str = SALT) -> str:
    u = uniform(purpose, *keys, salt=salt)
    return f"(-({scale}) * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"


def _dim(x: str, lo: float, hi: float, cells: int) -> tuple[str, str]:
    """(index, condition)."""
    return f"cast(least(floor(({x} - {lo!r}::DOUBLE) * {cells} / {hi - lo!r}::DOUBLE), {cells - 1}) AS INTEGER)", f"({x} >= {lo!r} AND {x} < {hi!r})"


SHIP = "date_diff('day', DATE '1995-01-01', l_shipdate::DATE)"
SECOND = "date_diff('microsecond', TIMESTAMP '2024-01-01', ts) / 1000000.0::DOUBLE"
_PRICE = ("l_extendedprice", 0.0, 105000.0, 1000)
_LINE = [("l_quantity", 1.0, 51.0, 10), ("l_extendedprice", 0.0, 105000.0, 10), ("l_discount", -0.005, 0.105, 11), ("l_tax", -0.005, 0.085, 9), (SHIP, 0.0, 2520.0, 10), ("l_linenumber", 1.0, 8.0, 7)]
_ORIGIN = [("s_nationkey", 0.0, 25.0, 25), ("s_acctbal", -1000.0, 10000.0, 20)]
_STOP = [("p_size", 1.0, 51.0, 10), ("p_retailprice", 900.0, 1000.0, 10)]
_TARGET = [("c_nationkey", 0.0, 25.0, 25), ("c_acctbal", -1000.0, 10000.0, 20)]
_OD = "lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"
_EVENTS = "(SELECT *, cast(json_extract_string(props, '$.k') AS INTEGER) AS k, ts::DATE AS dy, hour(ts) AS hr FROM events)"
_TRAJ4 = f"""(SELECT user_id, dy, first(value ORDER BY ts, event_id) AS a0, first(k ORDER BY ts, event_id) AS a1, last(value ORDER BY ts, event_id) AS a2, last(k ORDER BY ts, event_id) AS a3
  FROM {_EVENTS} GROUP BY user_id, dy HAVING count(*) >= 2)"""
_TRAJ6 = (
    "(SELECT user_id, dy, "
    + ", ".join(f"first({c} ORDER BY ts, event_id) FILTER (WHERE hr // 8 = {f}) AS a{2 * f + i}" for f in range(3) for i, c in enumerate(("value", "k")))
    + f" FROM {_EVENTS} GROUP BY user_id, dy HAVING count(DISTINCT hr // 8) = 3)"
)
_CONV = "(SELECT conv_id, " + ", ".join(f"max(role) FILTER (WHERE turn = {t}) AS r{t}" for t in (1, 2, 3)) + " FROM conversations GROUP BY conv_id)"

#: Source and dimensions (value, lo, hi, cells), or (index, condition) where an axis is a list of names.
MATRICES: dict[str, tuple[str, list[tuple]]] = {
    "price2": ("lineitem", [("l_quantity", 1.0, 51.0, 50), _PRICE]),
    "ship2": ("lineitem", [(SHIP, 0.0, 2520.0, 1000), _PRICE]),
    "clock2": ("events", [(SECOND, 0.0, 2592000.0, 1000), ("value", 0.0, 600.0, 1000)]),
    **{f"line{d}": ("lineitem", _LINE[:d]) for d in range(1, 7)},
    **{f"vec{d}": ("embeddings", [(f"embedding[{i + 1}]::DOUBLE", -0.6, 0.6, 30) for i in range(d)]) for d in range(2, 7)},
    "od4": (_OD, _ORIGIN + _TARGET),
    "od6": (_OD + " JOIN part ON l_partkey = p_partkey", _ORIGIN + _STOP + _TARGET),
    "traj4": (_TRAJ4, [(f"a{i}", 0.0, 100.0 if i % 2 else 600.0, 20) for i in range(4)]),
    "traj6": (_TRAJ6, [(f"a{i}", 0.0, 100.0 if i % 2 else 600.0, 10) for i in range(6)]),
    "docs2": ("documents", [("n_chars", 0.0, 150000.0, 100), ("cast(replace(source, 'src', '') AS INTEGER)", "source IN (" + ", ".join(f"'src{i}'" for i in range(20)) + ")")]),
    "quality2": ("documents LEFT JOIN labels USING (doc_id)", [("n_chars", 0.0, 150000.0, 20), ("quality", 0.0, 2.0, 2)]),
    "conv3": (_CONV, [(f"(CASE r{t} WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END)", f"r{t} IN ('system', 'user', 'assistant')") for t in (1, 2, 3)]),
    "pages1": ("pages", [("length(html)", 0.0, 80000.0, 100)]),
    "bench1": ("benchmark", [("length(text)", 0.0, 500.0, 50)]),
}
WIDTHS = {name: [dim[3] if len(dim) == 4 else {"docs2": 20, "conv3": 3}[name] for dim in dims] for name, (_, dims) in MATRICES.items()}
WIDTHS["partsupp2"] = [1000, 1000]


def cells(name: str, where: str = "true") -> str:
    """x1..xd, f."""
    if name == "partsupp2":
        n = {"l_partkey": "(SELECT count(*) FROM part)", "l_suppkey": "(SELECT count(*) FROM supplier)"}
        index = [(f"cast(floor(({k} - 0.0::DOUBLE) * 1000 / {c}::DOUBLE) AS INTEGER)", f"({k} >= 0 AND {k} < {c})") for k, c in n.items()]
        source = "lineitem"
    else:
        source, dims = MATRICES[name]
        index = [_dim(*dim) if len(dim) == 4 else dim for dim in dims]
    columns = ", ".join(f"{x} AS x{i}" for i, (x, _) in enumerate(index, 1))
    axes = ", ".join(f"x{i}" for i in range(1, len(index) + 1))
    return f"SELECT {axes}, count(*)::BIGINT AS f FROM (SELECT {columns} FROM {source} WHERE {' AND '.join(c for _, c in index)} AND {where}) GROUP BY {axes}"


# --- grids


def rule(kind: str, n: str, e: float, d: int, r: float | None = None) -> str:
    if kind == "entropy" or (kind == "error" and d == 1):
        return f"pow({n} * {e!r} / {math.sqrt(2)!r}, {2 / (3 * d)!r})"
    if kind == "error":
        a = f"{2 * (d - 1) / d!r} * {n} * {e!r} / 10.0"
        if r is not None:
            return f"pow(({a}) * {r ** (1 / d - 0.5)!r}, {2 / (3 * d - 2)!r})"
        return f"pow({a}, {2 / (3 * d - 2)!r}) * {d * (3 * d - 2) / (3 * d * d - 3 * d + 2)!r}"
    return f"(CASE WHEN {n} > exp(1) THEN pow({n} / sqrt(ln(greatest({n}, exp(1)))), {2 / (d + 2)!r}) ELSE 1.0 END)"


def grid(name: str, kind: str, eps: float, r: float | None = None, noisy: bool = True, prefix: str = "", source: str | None = None) -> str:
    """CTEs c, t, m and boxes b (lo1, hi1, .., n_entries, ncount) of an equal grid; names carry ``prefix``."""
    widths, e0, p = WIDTHS[name], eps * 0.01, prefix
    d, e = len(widths), eps - eps * 0.01
    method = {"log": "log_grid", "entropy": "entropy_grid", "error": f"uniform_grid({r},{10 / math.sqrt(2)})"}[kind]
    salt = key(method, eps, name, e0, "round", 1.0, "")
    g = rule(kind, "greatest(n, 0.0)", e, d, r)
    ms = ", ".join(f"cast(greatest(1, least(round(g), {w})) AS BIGINT) AS m{i}" for i, w in enumerate(widths, 1))
    js = ", ".join(f"(((x{i} + 1) * m{i} - 1) // {w}) AS j{i}" for i, w in enumerate(widths, 1))
    domain = " CROSS JOIN ".join(f"(SELECT unnest(range(0, (SELECT m{i} FROM {p}m))) AS j{i})" for i in range(1, d + 1))
    js_ = [f"j{i}" for i in range(1, d + 1)]
    bounds = ", ".join(f"cast(j{i} * {w} // m{i} AS INTEGER) AS lo{i}, cast((j{i} + 1) * {w} // m{i} AS INTEGER) AS hi{i}" for i, w in enumerate(widths, 1))
    size = " * ".join(f"(hi{i} - lo{i})" for i in range(1, d + 1))
    drawn = laplace("count", f"1 / {e!r}", *js_, salt=salt) if noisy else "0.0"
    return f"""{p}c AS ({source or cells(name)}), {p}t AS (SELECT coalesce(sum(f), 0) + {laplace("total", f"1 / {e0!r}", salt=total_key(salt, e0))} AS n FROM {p}c),
      {p}m AS (SELECT {ms} FROM (SELECT {g} AS g FROM {p}t)),
      {p}k AS (SELECT {", ".join(js_)}, sum(f) AS cnt FROM (SELECT {js}, f FROM {p}c, {p}m) GROUP BY {", ".join(js_)}),
      {p}b AS (SELECT *, cast({size} AS DOUBLE) AS n_entries, 'g.' || {" || '.' || ".join(js_)} AS pid, 1 AS depth, coalesce(cnt, 0) + {drawn} AS ncount
        FROM (SELECT {", ".join(js_)}, {bounds}, cnt FROM ({domain}) CROSS JOIN {p}m LEFT JOIN {p}k USING ({", ".join(js_)})))"""


def single(name: str, eps: float, prefix: str = "", noisy: bool = True) -> str:
    widths, p = WIDTHS[name], prefix
    bounds = ", ".join(f"0 AS lo{i}, {w} AS hi{i}" for i, w in enumerate(widths, 1))
    drawn = laplace("leaf", f"1 / {eps!r}", "'r'", salt=key("one_box", eps, name, 1.0, "")) if noisy else "0.0"
    return f"{p}b AS (SELECT {bounds}, {float(math.prod(widths))!r}::DOUBLE AS n_entries, 'r' AS pid, 0 AS depth, coalesce(sum(f), 0) + {drawn} AS ncount FROM ({cells(name)}))"


def every_cell(name: str, eps: float, prefix: str = "", noisy: bool = True) -> str:
    widths, p = WIDTHS[name], prefix
    axes = [f"x{i}" for i in range(1, len(widths) + 1)]
    domain = " CROSS JOIN ".join(f"(SELECT unnest(range(0, {w})) AS x{i})" for i, w in enumerate(widths, 1))
    bounds = ", ".join(f"cast({x} AS INTEGER) AS lo{x[1:]}, cast({x} + 1 AS INTEGER) AS hi{x[1:]}" for x in axes)
    drawn = laplace("cell", f"1 / {eps!r}", *axes, salt=key("cell_noise", eps, name, 1.0, "")) if noisy else "0.0"
    return f"{p}b AS (SELECT {bounds}, 1.0::DOUBLE AS n_entries, 'c.' || {" || '.' || ".join(axes)} AS pid, 1 AS depth, coalesce(f, 0) + {drawn} AS ncount FROM ({domain}) LEFT JOIN ({cells(name)}) USING ({', '.join(axes)}))"


# --- trees, one common table expression per step of a level


def tree(name: str, eps: float, stop: str = "ncount < 1.0 * sqrt(2.0) / eps_k", homogeneous: bool = False, p: int = 5, q: float = 0.3, prefix: str = "", noisy: bool = True) -> str:
    """CTEs ending in b (bounds, n_entries, pid, depth, ncount) of a tree with the default options."""
    widths, x, e0 = WIDTHS[name], prefix, eps * 0.01
    d = len(widths)
    salt = key("tree", eps, name, ",".join(map(str, (stop, "redraw", "geometric", "net", 0.01, 1.0, *((p, q, "m", "composed", "share", "after") if homogeneous else ())))), "")
    bounds = [f"{s}{i}" for i in range(1, d + 1) for s in ("lo", "hi")]
    lists, leaves = [], []
    root = ", ".join(f"0 AS lo{i}, {w} AS hi{i}" for i, w in enumerate(widths, 1))
    lists.append(f"{x}cells0 AS (SELECT *, 'r' AS node FROM ({cells(name)}))")
    lists.append(f"{x}raw0 AS (SELECT 'r' AS node, {root}, coalesce(sum(f), 0) AS cnt, 0.0::DOUBLE AS acc, 1.0::DOUBLE AS m0 FROM {x}cells0)")
    weights = " + ".join(f"pow(m0, {j / 3!r})" for j in range(1, d + 1))
    for k in range(d):
        a = k + 1
        whole = f"{e0!r}::DOUBLE" if k == 0 else f"({eps - e0!r}::DOUBLE * pow(m0, {k / 3!r}) / ({weights}))"
        data = f"{whole} * {1 - q!r}" if homogeneous else whole
        prt = f"{whole} * {q!r}" if homogeneous else "0.0"
        width = f"(hi{a} - lo{a})"
        drawn = laplace("count", "1 / eps_k", "node", salt=salt) if noisy else "0.0"
        lists.append(f"{x}paid{k} AS (SELECT *, {data} AS eps_k, {prt} AS eps_prt, {eps!r}::DOUBLE - (acc + {whole}) AS eps_left, acc + {whole} AS acc2, {width} AS width FROM {x}raw{k})")
        lists.append(f"{x}noisy{k} AS (SELECT *, cnt + {drawn} AS ncount FROM {x}paid{k})")
        lists.append(f"{x}fan{k} AS (SELECT *, pow(greatest(ncount, 0.0) * eps_left / {math.sqrt(2)!r}, {2 / (3 * (d - k))!r}) AS g FROM {x}noisy{k})")
        m0 = "greatest(1.0, g)" if k == 0 else "m0"
        lists.append(f"{x}node{k} AS (SELECT * EXCLUDE (m0), {m0} AS m0, cast(greatest(1, least(round(g), width)) AS BIGINT) AS m FROM {x}fan{k})")
        last = laplace("leaf", "1 / eps_left", "node", salt=salt) if noisy else "0.0"
        leaves.append(f"SELECT node, {k} AS depth, {', '.join(bounds)}, cnt + {last} AS ncount FROM {x}node{k} WHERE {stop}")
        base = f"[lo{a} + j * width // m FOR j IN range(0, m + 1)]"
        if homogeneous:
            u = uniform("pos", "node", "t", "j", salt=salt)
            lists.append(f"{x}base{k} AS (SELECT *, {base} AS base FROM {x}node{k} WHERE NOT ({stop}))")
            lists.append(f"{x}pos{k} AS (SELECT node, t, lo{a} AS lo, hi{a} AS hi, base[j + 1] + cast(floor({u} * (base[j + 2] - base[j + 1])) AS BIGINT) AS c FROM {x}base{k} CROSS JOIN (SELECT unnest(range(1, {p + 1})) AS t) CROSS JOIN LATERAL (SELECT unnest(range(0, m)) AS j))")
            lists.append(f"{x}cand{k} AS (SELECT node, t, list_concat(list_concat([lo], list_sort(coalesce(list(DISTINCT c) FILTER (WHERE c > lo), []))), [hi]) AS ends FROM {x}pos{k} GROUP BY node, t, lo, hi)")
            lists.append(f"{x}slab{k} AS (SELECT c.node, c.t, len(list_filter(c.ends, lambda z: z <= s.x{a})) AS i, s.f, count(*) AS n FROM {x}cells{k} s JOIN {x}cand{k} c USING (node) GROUP BY ALL)")
            area = " * ".join([f"(hi{i} - lo{i})::DOUBLE" for i in range(1, d + 1) if i != a] or ["1.0"])
            lists.append(f"{x}mean{k} AS (SELECT s.node, s.t, s.i, sum(s.n) AS nz, (any_value(c.ends[s.i + 1]) - any_value(c.ends[s.i])) * any_value({area}) AS size, sum(s.f * s.n) / ((any_value(c.ends[s.i + 1]) - any_value(c.ends[s.i])) * any_value({area})) AS mu FROM {x}slab{k} s JOIN {x}cand{k} c ON c.node = s.node AND c.t = s.t JOIN {x}node{k} v ON v.node = s.node GROUP BY s.node, s.t, s.i)")
            lists.append(f"{x}off{k} AS (SELECT s.node, s.t, s.i, sum(s.n * abs(s.f - m.mu)) + any_value((m.size - m.nz) * m.mu) AS dev FROM {x}slab{k} s JOIN {x}mean{k} m USING (node, t, i) GROUP BY s.node, s.t, s.i)")
            drawn_c = laplace("cand", f"{2.0 * p!r} / v.eps_prt", "c.node", "c.t", salt=salt) if noisy else "0.0"
            lists.append(f"{x}obj{k} AS (SELECT c.node, c.t, any_value(c.ends) AS ends, coalesce(sum(o.dev), 0) + any_value({drawn_c}) AS o FROM {x}cand{k} c JOIN {x}node{k} v ON v.node = c.node LEFT JOIN {x}off{k} o ON o.node = c.node AND o.t = c.t GROUP BY c.node, c.t)")
            lists.append(f"{x}open{k} AS (SELECT n.*, w.ends FROM {x}node{k} n JOIN (SELECT node, first(ends ORDER BY o, t) AS ends FROM {x}obj{k} GROUP BY node) w USING (node))")
            j = f"len(list_filter(o.ends, lambda z: z <= s.x{a})) - 1"
        else:
            lists.append(f"{x}open{k} AS (SELECT *, {base} AS ends FROM {x}node{k} WHERE NOT ({stop}))")
            j = f"((s.x{a} - o.lo{a} + 1) * o.m - 1) // o.width"
        axes = ", ".join(f"s.x{i}" for i in range(1, d + 1))
        lists.append(f"{x}cells{a} AS (SELECT {axes}, s.f, s.node || '.' || ({j}) AS node FROM {x}cells{k} s JOIN {x}open{k} o USING (node))")
        same = ", ".join(c for c in bounds if c not in (f"lo{a}", f"hi{a}"))
        same = same + ", " if same else ""
        lists.append(f"{x}kids{a} AS (SELECT node || '.' || j AS node, {same}ends[j + 1] AS lo{a}, ends[j + 2] AS hi{a}, acc2 AS acc, m0 FROM (SELECT *, unnest(range(0, len(ends) - 1)) AS j FROM {x}open{k}))")
        lists.append(f"{x}raw{a} AS (SELECT k.*, coalesce(c.cnt, 0) AS cnt FROM {x}kids{a} k LEFT JOIN (SELECT node, sum(f) AS cnt FROM {x}cells{a} GROUP BY node) c USING (node))")
    last = laplace("leaf", f"1 / ({eps!r}::DOUBLE - acc)", "node", salt=salt) if noisy else "0.0"
    leaves.append(f"SELECT node, {d} AS depth, {', '.join(bounds)}, cnt + {last} AS ncount FROM {x}raw{d}")
    sizes = " * ".join(f"(hi{i} - lo{i})" for i in range(1, d + 1))
    typed = ", ".join(f"cast({c} AS INTEGER) AS {c}" for c in bounds)
    lists.append(f"{x}b AS (SELECT node AS pid, depth, {typed}, cast({sizes} AS DOUBLE) AS n_entries, ncount FROM ({' UNION ALL '.join(leaves)}))")
    return ", ".join(lists)


def released(ctes: str, d: int) -> str:
    bounds = ", ".join(f"{s}{i}" for i in range(1, d + 1) for s in ("lo", "hi"))
    return f"WITH {ctes} SELECT pid, {bounds}, n_entries, round(ncount, 6) AS ncount, depth FROM b"


# --- queries and answers


def _ids(n: int, ids: str | None) -> str:
    return ids or f"SELECT unnest(range(0, {n})) AS qid"


def random_queries(name: str, n: int, ids: str | None = None) -> str:
    columns = []
    for i, w in enumerate(WIDTHS[name], 1):
        a, b = (f"cast(floor({uniform('query', 'qid', str(i), str(k))} * {w}) AS INTEGER)" for k in (1, 2))
        columns += [f"least({a}, {b}) AS qlo{i}", f"greatest({a}, {b}) + 1 AS qhi{i}"]
    return f"SELECT qid, {', '.join(columns)} FROM ({_ids(n, ids)})"


def coverage_queries(name: str, share: float, n: int, ids: str | None = None) -> str:
    columns = []
    for i, w in enumerate(WIDTHS[name], 1):
        side = max(1, int(share * w + 0.5))
        lo = f"cast(floor({uniform('query', 'qid', str(i), '1')} * {w - side + 1}) AS INTEGER)"
        columns += [f"{lo} AS qlo{i}", f"{lo} + {side} AS qhi{i}"]
    return f"SELECT qid, {', '.join(columns)} FROM ({_ids(n, ids)})"


def overlap(d: int) -> str:
    return " * ".join(f"greatest(0, least(hi{i}, qhi{i}) - greatest(lo{i}, qlo{i}))::DOUBLE" for i in range(1, d + 1))


def answers(boxes: str, queries: str, d: int) -> str:
    return f"SELECT q.qid, coalesce(sum(ncount * {overlap(d)} / n_entries), 0.0) AS est FROM {queries} q CROSS JOIN {boxes} GROUP BY q.qid"


def truth(cells_: str, queries: str, d: int) -> str:
    inside = " AND ".join(f"x{i} >= qlo{i} AND x{i} < qhi{i}" for i in range(1, d + 1))
    return f"SELECT q.qid, coalesce(sum(f), 0)::DOUBLE AS truth FROM {queries} q LEFT JOIN {cells_} ON {inside} GROUP BY q.qid"
