"""SQL texts for DuckDB that compute each query another way.

Least squares: by inverse variances of subtrees, not by the engine's two passes. Range answers: by descent
from the root, not by parents' boxes. Splits: by window functions over whole nodes, not by buckets.
"""

from __future__ import annotations

from noisytree.plans import budget, domain
from noisytree.plans.domain import Domain
from noisytree.sources.workloads import REPORTED, SHAPES

SEED = "7"


def dbl(x: float) -> str:
    return f"CAST('{float(x)!r}' AS DOUBLE)"


def uniform(*key: str) -> str:
    text = " || ':' || ".join(["'" + SEED + "'", *[f"CAST({k} AS VARCHAR)" for k in key]])
    return f"((('0x' || substr(md5({text}), 1, 13))::BIGINT::DOUBLE + 0.5::DOUBLE) / 4503599627370496::DOUBLE)"


def lap(u: str) -> str:
    """Unit Laplace noise from the name of a column of uniforms."""
    return f"(CASE WHEN {u} < 0.5 THEN ln(2 * {u}) ELSE -ln(2 * (1 - {u})) END)"


def gum(u: str) -> str:
    return f"(-ln(-ln({u})))"


DAY = "date_diff('day', DATE '1995-01-01', l_shipdate::DATE)"
POINTS = {
    "LI": f"SELECT concat_ws(':', l_orderkey, l_linenumber, round(l_extendedprice * 100)::BIGINT, {DAY}) AS pid, l_extendedprice::DOUBLE AS x, {DAY}::DOUBLE AS y FROM lineitem",
    "EV": "SELECT event_id::VARCHAR AS pid, date_diff('microsecond', TIMESTAMP '2024-01-01', ts)::DOUBLE / 86400000000::DOUBLE AS x, value::DOUBLE AS y FROM events",
    "CUST": "SELECT c_custkey::VARCHAR AS pid, c_acctbal::DOUBLE AS x, c_nationkey::DOUBLE AS y FROM customer",
    "SUPP": "SELECT s_suppkey::VARCHAR AS pid, s_acctbal::DOUBLE AS x, s_nationkey::DOUBLE AS y FROM supplier",
    "EMB": "SELECT vec_id::VARCHAR AS pid, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y, embedding[3]::DOUBLE AS z FROM embeddings",
}


def cell(v: str, lo: float, hi: float, n: int) -> str:
    return f"least({n - 1}, greatest(0, floor(({v} - {dbl(lo)}) / {dbl(hi - lo)} * {dbl(n)})::BIGINT))::BIGINT"


def interleave(ix: list[str], bits: int) -> str:
    d = len(ix)
    parts = [f"((({x} >> {k}) & 1) << {d * k + d - 1 - a})" for k in range(bits) for a, x in enumerate(ix)]
    return "(" + " + ".join(parts or ["0"]) + ")::BIGINT"


def bits_of(node: str, bits: int, d: int, a: int) -> str:
    return "(" + " + ".join([f"((({node} >> {d * k + d - 1 - a}) & 1) << {k})" for k in range(bits)] or ["0"]) + ")"


def leaves(view: str, dom: Domain, h: int, source: str | None = None) -> str:
    """pts, leaf (node_id, c)."""
    cells = [cell(a.name, a.lo, a.hi, 1 << h) for a in dom.axes]
    names = [f"i{k}" for k in range(dom.d)]
    return f"""pts AS ({source or POINTS[view]}),
ix AS (SELECT {", ".join(f"{c} AS {n}" for c, n in zip(cells, names, strict=True))} FROM pts),
leaf AS (SELECT {interleave(names, h)} AS node_id, count(*) AS c FROM ix GROUP BY 1)"""


def all_nodes(h: int, f: int) -> str:
    return " UNION ALL ".join(f"SELECT {level}::INTEGER AS level, range::BIGINT AS node_id FROM range({f ** (h - level)})" for level in range(h + 1))


def counts(view: str, dom: Domain, h: int, source: str | None = None) -> str:
    """nodes (level, node_id, c)."""
    d, f = dom.d, 1 << dom.d
    ups = " UNION ALL ".join(f"SELECT {level}::INTEGER AS level, (node_id >> {d * level})::BIGINT AS node_id, sum(c)::BIGINT AS c FROM leaf GROUP BY 2" for level in range(h + 1))
    return f"""{leaves(view, dom, h, source)},
up AS ({ups}), every AS ({all_nodes(h, f)}),
nodes AS (SELECT level, node_id, coalesce(c, 0)::BIGINT AS c FROM every LEFT JOIN up USING (level, node_id))"""


def noisy(eps: list[float], tree: str, src: str = "nodes", name: str = "noisy") -> str:
    case = "CASE level " + " ".join(f"WHEN {i} THEN {dbl(e)}" for i, e in enumerate(eps)) + " END"
    return f"""{name}_u AS (SELECT *, {uniform("'cnt'", f"'{tree}'", "level", "node_id")} AS u, {case} AS e FROM {src}),
{name} AS (SELECT * EXCLUDE (u), CASE WHEN e > 0 THEN c + (1 / e) * {lap("u")} END AS y FROM {name}_u)"""


def ols(eps: list[float], h: int, f: int = 4, src: str = "noisy", name: str = "fit") -> str:
    """name (level, node_id, beta): a node's best estimate from its subtree, then discrepancies shared."""
    bits = f.bit_length() - 1
    out = [f"{name}_z0 AS (SELECT node_id, y AS z, 0::DOUBLE AS cs FROM {src} WHERE level = 0)"]
    var = 2 / eps[0] ** 2
    for level in range(1, h + 1):
        below = f * var
        own = eps[level] ** 2 / 2
        a = own / (own + 1 / below)
        var = 1 / (own + 1 / below)
        out.append(f"{name}_s{level} AS (SELECT node_id >> {bits} AS node_id, sum(z) AS cs FROM {name}_z{level - 1} GROUP BY 1)")
        out.append(f"{name}_z{level} AS (SELECT n.node_id, {dbl(a)} * coalesce(n.y, 0) + {dbl(1 - a)} * s.cs AS z, s.cs FROM {src} n JOIN {name}_s{level} s USING (node_id) WHERE level = {level})")
    out.append(f"{name}_b{h} AS (SELECT node_id, z AS beta, cs FROM {name}_z{h})")
    for level in range(h - 1, -1, -1):
        out.append(f"{name}_b{level} AS (SELECT z.node_id, z.z + (p.beta - p.cs) / {f} AS beta, z.cs FROM {name}_z{level} z JOIN {name}_b{level + 1} p ON p.node_id = z.node_id >> {bits})")
    out.append(f"{name} AS (" + " UNION ALL ".join(f"SELECT {level}::INTEGER AS level, node_id::BIGINT AS node_id, beta FROM {name}_b{level}" for level in range(h + 1)) + ")")
    return ",\n".join(out)


def boxes(dom: Domain, count: int = 20) -> str:
    parts = []
    for s, shape in enumerate(REPORTED):
        cols = []
        for a, axis in enumerate(dom.axes):
            extent = SHAPES[shape][a % 2] * axis.width
            lo = f"{dbl(axis.lo)} + {uniform(chr(39) + 'box' + chr(39), chr(39) + shape + chr(39), 'range', str(a))} * {dbl(axis.width - extent)}"
            cols.append(f"{lo} AS q{axis.name}0, {lo} + {dbl(extent)} AS q{axis.name}1")
        parts.append(f"SELECT ({s * count} + range)::BIGINT AS qid, '{shape}' AS shape, {', '.join(cols)} FROM range({count})")
    return "boxes AS (" + " UNION ALL ".join(parts) + ")"


def exact_answers(dom: Domain) -> str:
    cond = " AND ".join(f"p.{n} >= q.q{n}0 AND p.{n} < q.q{n}1" for n in dom.names)
    return f"truth AS (SELECT qid, count(p.pid) AS true_count FROM boxes q LEFT JOIN pts p ON {cond} GROUP BY qid)"


def node_box(dom: Domain, h: int, level: int, node: str = "node_id") -> str:
    cols = []
    for k, a in enumerate(dom.axes):
        at = bits_of(node, h, dom.d, k)
        cols += [f"{dbl(a.lo)} + {dbl(a.hi - a.lo)} * ({at} + {e}) / {dbl(2 ** (h - level))} AS {a.name}{e}" for e in (0, 1)]
    return ", ".join(cols)


def descent(dom: Domain, h: int, values: str, name: str = "hit", skipped: tuple[int, ...] = ()) -> str:
    """name (qid, level, node_id, part): by descent. values (level, node_id, value) tells which levels count."""
    f, d = 1 << dom.d, dom.d
    inside = " AND ".join(f"{n}0 >= q{n}0 AND {n}1 <= q{n}1" for n in dom.names)
    over = " AND ".join(f"{n}0 < q{n}1 AND {n}1 > q{n}0" for n in dom.names)
    frac = " * ".join(f"((least({n}1, q{n}1) - greatest({n}0, q{n}0)) / ({n}1 - {n}0))" for n in dom.names)
    qcols = ", ".join(f"q{c}" for c in dom.box)
    out, emit = [], []
    for level in range(h, -1, -1):
        up = f"SELECT 0::BIGINT AS node_id, qid, {qcols} FROM boxes" if level == h else f"SELECT (f.node_id * {f} + g.range)::BIGINT AS node_id, qid, {qcols} FROM {name}_f{level + 1} f, range({f}) g WHERE NOT done"
        done = f"({inside})" if level not in skipped else "false"
        out.append(f"{name}_c{level} AS ({up})")
        out.append(f"{name}_f{level} AS (SELECT *, {done} AS done FROM (SELECT *, {node_box(dom, h, level)} FROM {name}_c{level}) WHERE {over})")
        part = f"CASE WHEN done THEN 1::DOUBLE ELSE {frac} END" if level == 0 else "1::DOUBLE"
        emit.append(f"SELECT qid, {level}::INTEGER AS level, node_id, {part} AS part FROM {name}_f{level}" + ("" if level == 0 else " WHERE done"))
    out.append(f"{name} AS (" + " UNION ALL ".join(emit) + ")")
    return ",\n".join(out)


def answers(values: str, column: str, name: str = "ans", hit: str = "hit") -> str:
    return f"{name} AS (SELECT b.qid, coalesce(sum(v.{column} * t.part), 0) AS estimate FROM boxes b LEFT JOIN {hit} t USING (qid) LEFT JOIN {values} v ON v.level = t.level AND v.node_id = t.node_id GROUP BY b.qid)"


# -- medians and splits ---------------------------------------------------------------------------
def ranked(values: str, bounds: str, name: str) -> str:
    """name_t (node_id, lo, hi, n, first) and name_g (node_id, n, k, l, r): gaps. values: node_id, v."""
    return f"""{name}_v AS (SELECT b.node_id, least(greatest(v, b.lo), b.hi) AS v FROM {values} JOIN {bounds} b USING (node_id)),
{name}_m AS (SELECT node_id, v, count(*) AS c FROM {name}_v GROUP BY ALL),
{name}_k AS (SELECT node_id, v, sum(c) OVER w AS k, lead(v) OVER w AS nxt FROM {name}_m WINDOW w AS (PARTITION BY node_id ORDER BY v)),
{name}_t AS (SELECT b.node_id, b.lo, b.hi, coalesce(sum(c), 0)::BIGINT AS n, coalesce(min(v), any_value(b.hi)) AS first FROM {bounds} b LEFT JOIN {name}_m USING (node_id) GROUP BY b.node_id, b.lo, b.hi),
{name}_g AS (SELECT * FROM (SELECT node_id, n, 0::BIGINT AS k, lo AS l, first AS r FROM {name}_t UNION ALL SELECT node_id, n, k::BIGINT, v, coalesce(nxt, hi) FROM {name}_k JOIN {name}_t USING (node_id)) WHERE r > l)"""


MID = "floor((n + 1) / 2.0)::BIGINT"


def em(values: str, bounds: str, eps: float, tree: str, depth: int, name: str) -> str:
    """name (node_id, split) by the exponential mechanism."""
    return f"""{ranked(values, bounds, name)},
{name}_u AS (SELECT *, {uniform("'gum'", f"'{tree}'", str(depth), "node_id", "k")} AS u FROM {name}_g),
{name}_s AS (SELECT *, ln(r - l) - {dbl(eps)} * abs(k - {MID}) / 2 + {gum("u")} AS score FROM {name}_u),
{name}_w AS (SELECT node_id, arg_max(l, score) AS l, arg_max(r, score) AS r FROM {name}_s GROUP BY 1),
{name} AS (SELECT b.node_id, least(greatest(coalesce(l + {uniform("'uni'", f"'{tree}'", str(depth), "b.node_id")} * (r - l), b.lo), b.lo), b.hi) AS split FROM {bounds} b LEFT JOIN {name}_w USING (node_id))"""


def median(values: str, bounds: str, name: str) -> str:
    return f"""{ranked(values, bounds, name)},
{name} AS (SELECT t.node_id, coalesce(min(v), (any_value(lo) + any_value(hi)) / 2) AS split, any_value(n) AS n FROM {name}_t t LEFT JOIN {name}_k k ON k.node_id = t.node_id AND k.k >= {MID} GROUP BY 1)"""


def mean(values: str, bounds: str, eps: float, tree: str, depth: int, name: str) -> str:
    return f"""{name}_a AS (SELECT b.node_id, b.lo, b.hi, coalesce(sum((least(greatest(v, b.lo), b.hi) - b.lo)::DECIMAL(28,6)), 0)::DOUBLE AS s, count(v) AS n FROM {bounds} b LEFT JOIN {values} USING (node_id) GROUP BY ALL),
{name}_u AS (SELECT *, {uniform("'sum'", f"'{tree}'", str(depth), "node_id")} AS us, {uniform("'num'", f"'{tree}'", str(depth), "node_id")} AS un FROM {name}_a),
{name}_n AS (SELECT *, s + ((hi - lo) / {dbl(eps * 0.5)}) * {lap("us")} AS ns, n + {dbl(1 / (eps * 0.5))} * {lap("un")} AS nn FROM {name}_u),
{name} AS (SELECT node_id, least(greatest(CASE WHEN nn > 0 THEN lo + ns / nn ELSE (lo + hi) / 2 END, lo), hi) AS split FROM {name}_n)"""


def kd(dom: Domain, depth: int, stage, h_counts: bool = True, src: str = "pts0") -> str:
    """p<b> (pid, coordinates, node_id) and b<b> (node_id, box) for each binary depth, by stage(values,
    bounds, depth, name). src: pid and clamped coordinates."""
    coords = ", ".join(dom.names)
    ends = ", ".join(f"{dbl((a.lo, a.hi)[e])} AS {a.name}{e}" for a in dom.axes for e in (0, 1))
    out = [f"p0 AS (SELECT pid, {coords}, 0::BIGINT AS node_id FROM {src})", f"b0 AS (SELECT 0::BIGINT AS node_id, {ends})"]
    for b in range(depth):
        ax = dom.axes[b % dom.d].name
        out.append(f"v{b} AS (SELECT node_id, {ax} AS v FROM p{b})")
        out.append(f"o{b} AS (SELECT node_id, {ax}0 AS lo, {ax}1 AS hi FROM b{b})")
        out.append(stage(f"v{b}", f"o{b}", b, f"s{b}"))
        out.append(f"p{b + 1} AS (SELECT pid, {coords}, node_id * 2 + CASE WHEN {ax} >= split THEN 1 ELSE 0 END AS node_id FROM p{b} JOIN s{b} USING (node_id))")
        keep = ", ".join(c for c in dom.box if c != f"{ax}1")
        keep2 = ", ".join(c for c in dom.box if c != f"{ax}0")
        out.append(f"b{b + 1} AS (SELECT node_id * 2 AS node_id, {keep}, split AS {ax}1 FROM b{b} JOIN s{b} USING (node_id) UNION ALL BY NAME SELECT node_id * 2 + 1 AS node_id, {keep2}, split AS {ax}0 FROM b{b} JOIN s{b} USING (node_id))")
    return ",\n".join(out)


def clamped(view: str, dom: Domain) -> str:
    cols = ", ".join(f"least(greatest({a.name}, {dbl(a.lo)}), {dbl(a.hi)}) AS {a.name}" for a in dom.axes)
    return f"pts AS ({POINTS[view]}), pts0 AS (SELECT pid, {cols} FROM pts)"


def kd_nodes(dom: Domain, h: int) -> str:
    """tree (level, node_id, box, c) of the flattened tree of 2 h binary levels."""
    box = ", ".join(dom.box)
    parts = [f"SELECT {level}::INTEGER AS level, b.node_id, {box}, (SELECT count(*) FROM p{2 * h} p WHERE p.node_id >> {2 * level} = b.node_id) AS c FROM b{2 * (h - level)} b" for level in range(h + 1)]
    return "tree AS (" + " UNION ALL ".join(parts) + ")"


def rounded(dom: Domain, *more: str) -> str:
    return ", ".join([f"round({c}, 6) + 0 AS {c}" for c in dom.box] + list(more))


LI, EV, EMB, CUST = domain.LI, domain.EV, domain.EMB, domain.CUST
HV = Domain((domain.Axis("h", 0.0, float(4**18)),))


def hilbert(order: int = 18) -> str:
    """curve (pid, x, y, hv): one step of the recursion a bit."""
    n = 1 << order
    return f"""curve0 AS (SELECT pid, x, y, {cell("x", EV.axes[0].lo, EV.axes[0].hi, n)} AS cx, {cell("y", EV.axes[1].lo, EV.axes[1].hi, n)} AS cy FROM pts),
walk AS (
  SELECT pid, x, y, cx AS px, cy AS py, {n // 2}::BIGINT AS s, 0::BIGINT AS hv FROM curve0
  UNION ALL
  SELECT pid, x, y,
    CASE WHEN ry = 0 THEN CASE WHEN rx = 1 THEN s - 1 - (py - ry * s) ELSE py - ry * s END ELSE px - rx * s END,
    CASE WHEN ry = 0 THEN CASE WHEN rx = 1 THEN s - 1 - (px - rx * s) ELSE px - rx * s END ELSE py - ry * s END,
    s // 2, hv + s * s * (CASE WHEN rx = 1 THEN 3 - ry ELSE ry END)
  FROM (SELECT *, CASE WHEN px >= s THEN 1 ELSE 0 END AS rx, CASE WHEN py >= s THEN 1 ELSE 0 END AS ry FROM walk WHERE s > 0)
),
curve AS (SELECT pid, x, y, hv FROM walk WHERE s = 0)"""


def smooth_sigma(xi: float) -> str:
    return f"""WITH v AS (SELECT c_nationkey::BIGINT AS node_id, least(greatest(c_acctbal, -1000), 10000)::DOUBLE AS v FROM customer),
n AS (SELECT node_id, count(*) AS n, floor((count(*) + 1) / 2.0)::BIGINT AS m FROM v GROUP BY 1),
x AS (
  SELECT node_id, row_number() OVER (PARTITION BY node_id ORDER BY v) AS i, v FROM v
  UNION ALL SELECT node_id, 0, -1000 FROM n UNION ALL SELECT node_id, n + 1, 10000 FROM n
)
SELECT a.node_id AS nationkey, round(max(exp(-(b.i - a.i - 1) * {dbl(xi)}) * (b.v - a.v)), 6) AS sigma
FROM n JOIN x a ON a.node_id = n.node_id AND a.i <= n.m JOIN x b ON b.node_id = n.node_id AND b.i >= n.m AND b.i > a.i GROUP BY 1"""


VAL = """types AS (SELECT event_type, (row_number() OVER (ORDER BY event_type) - 1)::BIGINT AS node_id FROM (SELECT DISTINCT event_type FROM events)),
val AS (SELECT node_id, event_id, value::DOUBLE AS v FROM events JOIN types USING (event_type)),
bnd AS (SELECT node_id, 0::DOUBLE AS lo, 640::DOUBLE AS hi FROM types)"""


def geometric(h: int, eps: float = 1.0, d: int = 2) -> list[float]:
    return budget.geometric(eps, h, 1 << d, d)
